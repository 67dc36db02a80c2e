"""Name -> query, and name -> the same in DuckDB SQL."""

from __future__ import annotations

from . import queries_features, queries_graph, queries_models, queries_more, queries_tasks

QUERIES = {**queries_tasks.QUERIES, **queries_graph.QUERIES, **queries_features.QUERIES, **queries_more.QUERIES, **queries_models.QUERIES}
ORACLE = {**queries_tasks.ORACLE, **queries_graph.ORACLE, **queries_features.ORACLE, **queries_more.ORACLE, **queries_models.ORACLE}
