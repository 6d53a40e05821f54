"""Experiment workloads and relational operators as driver queries with their SQL twins."""

from __future__ import annotations

from assetmill.workloads import blocks, curation, evaluation, extensions, network, relational, rendering, shaping, streams


def flagship(spark, sf_dir):
    return curation.flagship(spark, sf_dir)


def _all() -> dict:
    return {**curation.QUERIES, **network.QUERIES, **evaluation.QUERIES, **relational.QUERIES, **streams.QUERIES, **rendering.QUERIES, **extensions.QUERIES, **shaping.QUERIES, **blocks.QUERIES}


def queries() -> dict:
    return {k: f for k, (f, _) in _all().items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for k, (_, s) in _all().items() if s}
