"""SQL surface: MATCH queries on a named graph, and table functions for single documents."""

from __future__ import annotations

import json
import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from treelogic.evaluate.engine import evaluate
from treelogic.graph.model import PropertyGraph
from treelogic.query.dsl import parse
from treelogic.query.pattern import TreePattern

_MATCH = re.compile(r"\s*match\s+(?P<pattern>.+?)(?:\s+return\s+(?P<columns>[\w\s.,]+))?\s*;?\s*", re.I | re.S)


def sql(graph: PropertyGraph, text: str, view: str | None = None, **options) -> DataFrame:
    """``MATCH <pattern> RETURN o.o_orderkey, c.c_name``: answers of a pattern in its text form.

    Without RETURN the outputs' node ids come back; ``view`` registers the result.
    """
    m = _MATCH.fullmatch(text)
    if not m:
        raise ValueError("expected MATCH <pattern> [RETURN <node>.<attribute>, ...]")
    pattern = parse(m["pattern"])
    project: dict[str, list[str]] = {}
    for item in (m["columns"] or "").split(","):
        if item.strip():
            name, _, attribute = item.strip().partition(".")
            project.setdefault(name, []).append(attribute or "node_id")
    if unknown := set(project) - set(pattern.nodes):
        raise ValueError(f"RETURN names {sorted(unknown)}, which are not in the pattern")
    if project:
        pattern = pattern.with_outputs(project)
    df = evaluate(graph, pattern, project=project or None, **options).df
    if view:
        df.createOrReplaceTempView(view)
    return df


@udtf(returnType="pre int, post int, level int, parent int, tag string, href string, chars int")
class ParseDom:
    """The elements of one page."""

    def eval(self, html: str):
        from treelogic.graph.catalog import dom_rows

        rows = dom_rows(0, html)
        for r in rows:
            yield (*r[2:5], 0 if r[5] is None else rows[r[5]][2], *r[6:])


@udtf(returnType="match string")
class TreeMatch:
    """Answers of a pattern (text form) on one page's elements: JSON of output -> pre number."""

    def eval(self, html: str, pattern: str):
        from treelogic.graph.catalog import dom_rows
        from treelogic.query.reference import SmallGraph, evaluate as small

        rows = dom_rows(0, html)
        nodes = {r[2]: ("element", {"tag": r[6], "href": r[7], "chars": r[8]}) for r in rows}
        p: TreePattern = parse(pattern)
        for found in sorted(small(SmallGraph(nodes, {(rows[r[5]][2], r[2]) for r in rows if r[5] is not None}), p)):
            yield (json.dumps(dict(zip(p.outputs(), found))),)


def register(spark: SparkSession) -> None:
    """Makes ``parse_dom(html)`` and ``tree_match(html, pattern)`` callable from SQL."""
    spark.udtf.register("parse_dom", ParseDom)
    spark.udtf.register("tree_match", TreeMatch)
