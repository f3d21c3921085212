"""proxigraph: proximity-graph vector search and large-scale corpus operators on PySpark DataFrames."""
