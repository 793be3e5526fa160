"""Relationship queries on large labelled graphs, expressed as Spark DataFrame plans."""
