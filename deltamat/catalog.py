"""All named queries of the reference's operators, with the SQL that checks them."""

from __future__ import annotations

from importlib import import_module

from deltamat.queries import base

MODULES = ("matrices", "products", "measures", "surface")


def _load() -> None:
    for m in MODULES:
        import_module(f"deltamat.queries.{m}")


def queries():
    _load()
    return base.QUERIES


def oracle_sql():
    _load()
    return base.ORACLES


def flagship(spark, sf_dir):
    from deltamat.queries.products import flagship as run

    return run(spark, sf_dir)
