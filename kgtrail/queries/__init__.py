"""Registered queries, by area, each with its DuckDB twin where SQL can express it."""

from kgtrail.queries import experiments, extensions, ontology, refinement, retrieval, surface, tables, types  # noqa: F401
