"""The queries of this subpackage, and the SQL of those that SQL can express."""

from __future__ import annotations

import importlib

MODULES = ("langid", "mixing", "chat", "suffix_dedup", "pieces", "url_filter", "quality", "simhash", "media", "line_dedup")


def _all(what: str) -> dict:
    return {k: v for m in MODULES for k, v in getattr(importlib.import_module(f"{__package__}.{m}"), what).items()}


def queries() -> dict:
    import corpus_pipeline

    return {**_all("QUERIES"), "pipeline": corpus_pipeline.run}


def oracles() -> dict[str, str]:
    return _all("ORACLES")
