"""The queries and SQL of this subpackage, for __spark_entry__.py."""

from __future__ import annotations

from . import decontaminate, hostrules, langid, linededup, packing, paritysketch, sharding, substringdedup, tokencount, urlfilter

MODULES = (tokencount, packing, urlfilter, langid, substringdedup, hostrules, linededup, paritysketch, decontaminate, sharding)


def queries() -> dict:
    return {k: f for m in MODULES for k, f in m.QUERIES.items()}


def oracles() -> dict[str, str]:
    return {k: s for m in MODULES for k, s in m.ORACLES.items()}
