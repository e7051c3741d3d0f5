"""Queries of the reference's methods by family, each with its oracle in DuckDB SQL where SQL can express it."""

from __future__ import annotations

from distds.queries import bloom, contigs, costs, kmers, queues, relational, sorting, space, streams, table

FAMILIES = (space, table, queues, bloom, sorting, kmers, contigs, costs, relational, streams)


def queries() -> dict:
    return {k: f for m in FAMILIES for k, f in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for m in FAMILIES for k, s in m.ORACLES.items()}
