"""Graphs: views on the given tables, edge-list files, a Python data source."""
