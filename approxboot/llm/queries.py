"""Registers the operators' queries and their SQL."""

from importlib import import_module

MODULES = ["secrets", "sharding", "token_store", "packing", "quality", "url_templates", "jaccard", "repeats", "nn_graph", "decontam"]

QUERIES: dict = {}
ORACLES: dict = {}
for _name in MODULES:
    _module = import_module(f"approxboot.llm.{_name}")
    QUERIES |= _module.QUERIES
    ORACLES |= _module.ORACLES
