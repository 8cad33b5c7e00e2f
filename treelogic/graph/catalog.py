"""The graphs that the given tables make.

``commerce``: region, nation, customer, supplier, part, orders, lineitem; tree
edges down to the lines and reference edges from a line to its part and
supplier.  ``activity``: users and events; author edges, the next event of the
same user and of the same topic.  ``papers``: a view of commerce as papers
(orders) with authors (lines, suppliers) and venues (customers).  ``trade``: a
cyclic graph of nations.  ``dom`` and ``thread``: pages' elements, and
conversations' turns.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from treelogic.graph.model import EdgeSet, PropertyGraph, Tables, global_id, natural_key, wide_id
from treelogic.plans import cut

CODES = {k: i for i, k in enumerate(("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "user", "event", "conversation", "turn"), 1)}


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def commerce(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Every node table carries the ids that its foreign keys name, in columns named after the edge sets.

    Lines have no key: a line's id is a hash of its whole row (full rows are
    distinct), which is read only where a query needs it.
    """
    keys = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey"}
    held = {  # edge set: source kind, target kind, role, end that holds the key, its column
        "region_nation": ("region", "nation", "tree", "target", "n_regionkey"),
        "nation_customer": ("nation", "customer", "tree", "target", "c_nationkey"),
        "nation_supplier": ("nation", "supplier", "tree", "target", "s_nationkey"),
        "customer_orders": ("customer", "orders", "tree", "target", "o_custkey"),
        "orders_lineitem": ("orders", "lineitem", "tree", "target", "l_orderkey"),
        "lineitem_part": ("lineitem", "part", "ref", "source", "l_partkey"),
        "lineitem_supplier": ("lineitem", "supplier", "ref", "source", "l_suppkey"),
    }
    def table(kind: str) -> DataFrame:
        rows = load(spark, sf_dir, kind)
        key = keys.get(kind)
        own = global_id(CODES[kind], F.col(key)) if key else wide_id(CODES[kind], sorted(rows.columns))
        more = {"node_id": own, "grp": F.pmod(F.col(key or "l_suppkey"), F.lit(10)).cast("int")}
        for name, (source, target, _, end, column) in held.items():
            if kind == (source if end == "source" else target):
                more[f"@{name}"] = global_id(CODES[target if end == "source" else source], F.col(column))
        return rows.select("*", *[c.alias(n) for n, c in more.items()])

    nodes = Tables({kind: lambda kind=kind: table(kind) for kind in [*keys, "lineitem"]})

    def edge(name: str) -> EdgeSet:
        source, target, role, end, _ = held[name]
        rows = nodes[source if end == "source" else target]
        own, other = F.col("node_id"), F.col(f"@{name}")
        df = rows.select((own if end == "source" else other).alias("src"), (other if end == "source" else own).alias("dst"))
        return EdgeSet(name, source, target, role, df, keyed=True, holder=end, column=f"@{name}", rows=rows)

    known = {kind: {key: lambda id_, kind=kind, key=key: natural_key(id_).cast(nodes[kind].schema[key].dataType)} for kind, key in keys.items()}
    return PropertyGraph(nodes, [edge(name) for name in held], known)


def papers(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Orders as papers: lines are authors, and a reference leads from a paper to its venue (customer)."""
    g = commerce(spark, sf_dir)
    orders = g.nodes["orders"]
    kept = [e for e in g.edges if e.name in ("orders_lineitem", "lineitem_supplier")]
    venue = EdgeSet("orders_customer", "orders", "customer", "ref", orders.select(F.col("node_id").alias("src"), F.col("@customer_orders").alias("dst")), keyed=True, holder="source", column="@customer_orders", rows=orders)
    return PropertyGraph({k: g.nodes[k] for k in ("orders", "lineitem", "supplier", "customer")}, [*kept, venue], g.keys)


def events(spark: SparkSession, sf_dir: str, below: int | None = None) -> DataFrame:
    rows = load(spark, sf_dir, "events")
    if below is not None:
        rows = rows.filter(F.col("event_id") < below)
    k = F.get_json_object("props", "$.k").cast("int")
    return rows.withColumn("k", k).withColumn("label", F.concat_ws("|", "event_type", k.cast("string"), F.pmod("user_id", F.lit(3)).cast("string")))


def activity(spark: SparkSession, sf_dir: str, below: int | None = None) -> PropertyGraph:
    """Users and events; ``below`` keeps the events with smaller ids (the slices of the tests' oracles)."""
    rows = events(spark, sf_dir, below).withColumn("node_id", global_id(CODES["event"], F.col("event_id")))
    users = rows.select("user_id").distinct().withColumn("node_id", global_id(CODES["user"], F.col("user_id")))

    def following(key: str) -> DataFrame:
        after = F.lead("node_id").over(Window.partitionBy(key).orderBy("ts", "event_id"))
        return rows.select(F.col("node_id").alias("src"), after.alias("dst")).filter("dst is not null")

    author = rows.select(global_id(CODES["user"], F.col("user_id")).alias("src"), F.col("node_id").alias("dst"))
    return PropertyGraph({"user": users, "event": rows}, [EdgeSet("author", "user", "event", "tree", author), EdgeSet("next_of_user", "event", "event", "ref", following("user_id")), EdgeSet("next_of_topic", "event", "event", "ref", following("k"))])


def trade(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Nations; an edge to the two nations whose suppliers sent most lines to the nation's customers."""
    lines = load(spark, sf_dir, "lineitem").join(load(spark, sf_dir, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(load(spark, sf_dir, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(load(spark, sf_dir, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    pairs = lines.filter("c_nationkey <> s_nationkey").groupBy("c_nationkey", "s_nationkey").count()
    place = F.row_number().over(Window.partitionBy("c_nationkey").orderBy(F.desc("count"), "s_nationkey"))
    edges = pairs.withColumn("place", place).filter("place <= 2").select(F.col("c_nationkey").cast("long").alias("src"), F.col("s_nationkey").cast("long").alias("dst"))
    nation = load(spark, sf_dir, "nation").withColumn("node_id", F.col("n_nationkey").cast("long"))
    return PropertyGraph({"nation": nation}, [EdgeSet("trades", "nation", "nation", "ref", edges)])


def thread(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Conversations: the conversation's node, then its turns in order."""
    turn = F.col("turn").cast("long")
    inside = F.when((turn >= 0) & (turn < F.lit(1 << 24)), F.col("conv_id").cast("long") * (1 << 24) + turn).otherwise(F.raise_error(F.lit("a conversation of 2**24 turns or more")).cast("long"))
    turns = load(spark, sf_dir, "conversations").withColumn("node_id", global_id(CODES["turn"], inside))
    heads = turns.select("conv_id").distinct().withColumn("node_id", global_id(CODES["conversation"], F.col("conv_id")))
    order = Window.partitionBy("conv_id").orderBy("turn")
    first = turns.withColumn("n", F.row_number().over(order)).filter("n = 1").select(global_id(CODES["conversation"], F.col("conv_id")).alias("src"), F.col("node_id").alias("dst"))
    after = turns.select(F.col("node_id").alias("src"), F.lead("node_id").over(order).alias("dst")).filter("dst is not null")
    return PropertyGraph({"conversation": heads, "turn": turns}, [EdgeSet("opens", "conversation", "turn", "tree", first), EdgeSet("goes_on", "turn", "turn", "tree", after)])


DOM_SCHEMA = "node_id long, page_id long, pre int, post int, level int, parent_id long, tag string, href string, chars int"
#: Elements of a page whose numbers fit into its ids.
DOM_BITS = 24


def dom_rows(page_id: int, html: str | None) -> list[tuple]:
    """The elements of a page in document order, numbered by entering and leaving."""
    from html.parser import HTMLParser

    rows: list[list] = []
    stack: list[int] = []
    clock = 0

    class Reader(HTMLParser):
        def handle_starttag(self, tag, attrs):
            nonlocal clock
            clock += 1
            if len(rows) >= 1 << DOM_BITS:
                raise ValueError(f"page {page_id} has 2**{DOM_BITS} elements or more")
            rows.append([(page_id << DOM_BITS) + len(rows), page_id, clock, clock, len(stack), rows[stack[-1]][0] if stack else None, tag, dict(attrs).get("href"), 0])
            if tag not in ("br", "meta", "link", "img", "input", "hr"):
                stack.append(len(rows) - 1)
            else:
                clock += 1
                rows[-1][3] = clock

        def handle_endtag(self, tag):
            nonlocal clock
            if any(rows[i][6] == tag for i in stack):
                while stack:
                    i = stack.pop()
                    clock += 1
                    rows[i][3] = clock
                    if rows[i][6] == tag:
                        break

        def handle_data(self, data):
            if stack:
                rows[stack[-1]][8] += len(data.strip())

    reader = Reader()
    reader.feed(html or "")
    reader.close()
    while stack:
        clock += 1
        rows[stack.pop()][3] = clock
    return [tuple(r) for r in rows]


def dom(spark: SparkSession, sf_dir: str) -> PropertyGraph:
    """Elements of all pages; tree edges only (``pre`` and ``post`` come with them).

    The pages are parsed once, into a table in the shared folder; an element
    carries its parent's id.
    """
    def parse(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        names = [c.split()[0] for c in DOM_SCHEMA.split(", ")]
        for batch in batches:
            out = pd.DataFrame([r for p, h in zip(batch["page_id"], batch["html"]) for r in dom_rows(int(p), h)], columns=names)
            yield out.astype({"parent_id": "Int64"})

    pages = load(spark, sf_dir, "pages").filter("page_id is not null").select("page_id", "html")
    nodes = cut(pages.mapInPandas(parse, DOM_SCHEMA)).withColumn("@inside", F.col("parent_id"))
    edges = nodes.filter("parent_id is not null").select(F.col("parent_id").alias("src"), F.col("node_id").alias("dst"))
    return PropertyGraph({"element": nodes}, [EdgeSet("inside", "element", "element", "tree", edges, keyed=True, holder="target", column="@inside", rows=nodes)])
