"""Queries of the training-data operators and their SQL."""

from __future__ import annotations

import importlib

_MODULES = ("quality_rules", "byte_bpe", "source_mix", "secret_scan", "spot_fingerprints", "token_files", "shingle_join", "language_model", "suffix_trees", "suffix_array")

QUERIES: dict = {}
ORACLES: dict = {}
for _name in _MODULES:
    _module = importlib.import_module(f"filterfleet.llm.{_name}")
    QUERIES.update(_module.QUERIES)
    ORACLES.update(_module.ORACLES)
