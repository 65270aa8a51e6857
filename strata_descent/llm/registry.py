"""Queries and SQL of the subpackage, by name."""

from __future__ import annotations

from . import fingerprints, importance, mixing, ngram_join, personal_data, pieces, quality_rules, substring_dedup, toxicity, url_filters


def pipeline(spark, sf_dir: str):
    """All stages of the corpus pipeline.  Its module lies at the repository's top and is looked up when asked for."""
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


_MODULES = (fingerprints, importance, mixing, ngram_join, personal_data, pieces, quality_rules, substring_dedup, toxicity, url_filters)
QUERIES = {name: query for module in _MODULES for name, query in module.QUERIES.items()} | {"pipeline": pipeline}
ORACLES = {name: sql for module in _MODULES for name, sql in module.ORACLES.items()}
