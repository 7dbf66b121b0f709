"""Shortest-path load (vertex and edge betweenness) on evolving graphs, for PySpark."""
