"""Tree patterns with Boolean logic over graphs, evaluated with Spark DataFrames."""
