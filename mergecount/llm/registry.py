"""Queries of this subpackage and the SQL that checks them."""

from __future__ import annotations

import importlib

#: module, query
OPERATORS = (
    ("pii", "op1_pii_pseudonyms"),
    ("kdsearch", "op2_kdtree_topk"),
    ("matroska", "op3_matroska_column"),
    ("packing", "op4_mixture_packing"),
    ("mixing", "op5_apportioned_mix"),
    ("warc", "op6_warc_chunks"),
    ("sharding", "op7_stratified_shards"),
    ("simhash", "op8_simhash_anchors"),
    ("licences", "op9_license_scan"),
    ("toxicity", "op10_toxicity_weak"),
)


def queries() -> dict:
    return {name: getattr(importlib.import_module(f"{__package__}.{module}"), name) for module, name in OPERATORS}


def oracle_sql() -> dict[str, str]:
    """SQL by query name, for the operators that SQL can express."""
    found = {name: importlib.import_module(f"{__package__}.{module}") for module, name in OPERATORS}
    return {name: m.oracle() for name, m in found.items() if hasattr(m, "oracle")}
