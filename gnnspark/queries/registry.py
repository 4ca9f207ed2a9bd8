"""All queries of the library proper."""

from __future__ import annotations

from . import base, caching, graphs, relational, running, sampling, streams, training, workloads  # noqa: F401


def queries():
    return dict(base.QUERIES)


def oracles():
    return dict(base.ORACLES)
