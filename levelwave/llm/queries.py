"""The queries of this folder and, where SQL can express one, its DuckDB text."""

from __future__ import annotations

from collections.abc import Callable
from importlib import import_module

from pyspark.sql import DataFrame, SparkSession

#: Module and function of each operator's query; the module's QUERY is its name and its SQL (if any) the oracle.
_MODULES = {"tokens": "op1", "minhash": "op2", "licenses": "op3", "packing": "op4", "langid": "op5", "quality": "op6", "bloom_lm": "op7", "toxicity": "op8", "bpe": "op9", "exact": "op10"}


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    import corpus_pipeline

    out = {}
    for module, function in _MODULES.items():
        m = import_module(f".{module}", __package__)
        out[m.QUERY] = getattr(m, function)
    return out | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    import corpus_pipeline

    modules = [import_module(f".{m}", __package__) for m in _MODULES]
    out = {m.QUERY: m.SQL for m in modules if getattr(m, "SQL", None)}
    return out | ({"pipeline": corpus_pipeline.ORACLE_SQL} if corpus_pipeline.ORACLE_SQL else {})
