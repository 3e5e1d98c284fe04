"""Queries of the training-data operators and their SQL, by name."""

from __future__ import annotations

from . import html_text, jaccard, license_scan, mixing, quality_model, quality_rules, repeats, sharding, tiling, url_filter

_MODULES = [quality_model, url_filter, tiling, mixing, sharding, jaccard, quality_rules, html_text, repeats, license_scan]


def queries():
    import corpus_pipeline

    out = {}
    for module in _MODULES:
        out.update(module.QUERIES)
    out["pipeline"] = corpus_pipeline.run
    return out


def oracle_sql():
    out = {}
    for module in _MODULES:
        out.update(module.ORACLE_SQL)
    return out
