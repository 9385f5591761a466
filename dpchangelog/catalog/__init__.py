"""Queries of the library and their SQL, by name."""


def load():
    from . import accounts, base, local_rr, log, ops, releases, workloads  # noqa: F401

    return base.QUERIES, base.SQL
