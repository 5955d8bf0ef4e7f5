"""Registered queries of the subpackage and their DuckDB twins, by operator module."""

from __future__ import annotations

from evigraph.llm import op1_transport, op2_language, op3_byte_bpe, op4_probminhash, op5_hilbert, op6_licenses, op7_simple8b, op8_weighted_sampling, op9_fuzzy_lines, op10_mixture

MODULES = [op1_transport, op2_language, op3_byte_bpe, op4_probminhash, op5_hilbert, op6_licenses, op7_simple8b, op8_weighted_sampling, op9_fuzzy_lines, op10_mixture]


def queries() -> dict:
    return {k: f for m in MODULES for k, f in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {k: s for m in MODULES for k, s in getattr(m, "ORACLES", {}).items()}
