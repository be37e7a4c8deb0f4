"""Formal-language path queries on labelled graphs, as Spark DataFrame plans."""
