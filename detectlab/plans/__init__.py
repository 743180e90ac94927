"""All queries, by section; each module has a registry R."""

from __future__ import annotations

from importlib import import_module

MODULES = ("q_corpus", "q_overlap", "q_generate", "q_scores", "q_project", "q_ops", "q_more")


def collect() -> tuple[dict, dict]:
    queries, oracles = {}, {}
    for name in MODULES:
        r = import_module(f"detectlab.plans.{name}").R
        if twice := queries.keys() & r.queries.keys():
            raise ValueError(f"registered twice: {sorted(twice)}")
        queries |= r.queries
        oracles |= r.oracles
    return queries, oracles
