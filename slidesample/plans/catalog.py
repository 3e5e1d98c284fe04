"""Every named query of the engine and the SQL it is compared with."""

from __future__ import annotations

from slidesample.plans import q_estimates, q_loop, q_runs, q_sampling, q_surface

_MODULES = [q_sampling, q_estimates, q_runs, q_loop, q_surface]


def flagship(spark, sf_dir):
    return queries()["combined_sum_by_window"](spark, sf_dir)


def queries():
    out = {}
    for m in _MODULES:
        out.update(m.QUERIES)
    return out


def oracle_sql():
    out = {}
    for m in _MODULES:
        out.update(m.ORACLE)
    return out
