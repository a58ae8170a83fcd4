"""Exact subgraph enumeration on Spark: every occurrence of a small labelled pattern in a large labelled directed graph."""

__version__ = "0.1.0"
