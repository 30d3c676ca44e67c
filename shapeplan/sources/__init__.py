"""Graphs: class tables, triples, corruption levels, statistics, readers and writers."""

from shapeplan.sources.graph import ClassTableSource, GraphSource, TripleSource, class_tables, corrupt

__all__ = ["ClassTableSource", "GraphSource", "TripleSource", "class_tables", "corrupt"]
