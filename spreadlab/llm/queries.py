"""Registered queries of the training-data operators, with DuckDB SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from spreadlab.llm import decontaminate, jaccard, mixing, quality, substrings, token_frames, topk, toxicity, url_templates, warc

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
for _module in (quality, topk, url_templates, toxicity, warc, mixing, jaccard, substrings, decontaminate, token_frames):
    QUERIES |= _module.QUERIES
    ORACLES |= getattr(_module, "ORACLES", {})
