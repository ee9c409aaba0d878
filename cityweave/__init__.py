"""Urban knowledge-graph engine on Spark: linking, virtual and materialised graphs, queries."""
