"""Queries of this subpackage, by contract name."""

from canopy.llm import (
    embedding_dedup,
    exact_dedup,
    lattice_lm,
    mixing,
    ngram_join,
    packing,
    secret_scan,
    substring_dedup,
    toxicity,
    url_filter,
)

QUERIES = {
    "op1_substring_dedup": substring_dedup.query,
    "op2_ngram_join": ngram_join.query,
    "op3_exact_dedup": exact_dedup.query,
    "op4_lattice_lm": lattice_lm.query,
    "op5_secret_scan": secret_scan.query,
    "op6_toxicity": toxicity.query,
    "op7_url_filter": url_filter.query,
    "op8_source_mixing": mixing.query,
    "op9_genetic_packing": packing.query,
    "op10_embedding_dedup": embedding_dedup.query,
}
ORACLES = {"op2_ngram_join": ngram_join.ORACLE, "op3_exact_dedup": exact_dedup.ORACLE}
