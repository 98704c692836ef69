"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from joindash.llm import decontaminate, licenses, packing, pii, quality_classifier, quality_rules, revisits, secrets, sharding, simhash

MODULES = (simhash, decontaminate, licenses, sharding, quality_classifier, quality_rules, packing, revisits, pii, secrets)


def queries() -> dict:
    return {name: f for m in MODULES for name, f in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for m in MODULES for name, sql in m.ORACLE_SQL.items()}
