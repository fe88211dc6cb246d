"""Queries over the given tables, one for each operator of this subpackage."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from semigrid.llm import exact_dedup, language_id, lm_scoring, packing, piece_codec, quality_rules, simhash_dedup, suffix_dedup, token_counts, url_filter
from semigrid.sources.tables import table


def vocabulary(name: str) -> str:
    """Place of a public vocabulary file on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    docs = lambda s, d: table(s, d, "documents")
    return {
        "op1_url_filter": lambda s, d: url_filter.url_filter(table(s, d, "pages")),
        "op2_exact_dedup": lambda s, d: exact_dedup.exact_dedup(docs(s, d)),
        "op3_lm_scoring": lambda s, d: lm_scoring.query(docs(s, d)),
        "op4_quality_rules": lambda s, d: quality_rules.digest(docs(s, d)),
        "op5_piece_codec": lambda s, d: piece_codec.piece_encode(docs(s, d), vocabulary("piece_bpe_32k.model"), digests=True),
        "op6_simhash_dedup": lambda s, d: simhash_dedup.simhash_components(docs(s, d)),
        "op7_suffix_dedup": lambda s, d: suffix_dedup.suffix_dedup(docs(s, d)),
        "op8_language_id": lambda s, d: language_id.query(docs(s, d)),
        "op9_token_counts": lambda s, d: token_counts.token_counts(docs(s, d), vocabulary("piece_bpe_32k.model")),
        "op10_packing": lambda s, d: packing.pack(docs(s, d), vocabulary("word_bpe_49k.json")),
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_url_filter": url_filter.oracle(), "op2_exact_dedup": exact_dedup.ORACLE, "op4_quality_rules": quality_rules.ORACLE}
