"""Operators on labelled graphs."""
