"""Shapes over graphs of triples: validation and evidence subgraphs on Spark."""
