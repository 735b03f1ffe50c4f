"""Registered queries and oracle SQL of the corpus operators."""

from . import bpe_sql, decontamination, jaccard_join, licenses, lm_scores, quality_rules, sharding, suffix_dedup, token_counts, token_file

_MODULES = (token_file, suffix_dedup, quality_rules, lm_scores, token_counts, bpe_sql, licenses, jaccard_join, sharding, decontamination)

QUERIES = {k: v for m in _MODULES for k, v in m.QUERIES.items()}
SQL = {k: v for m in _MODULES for k, v in getattr(m, "SQL", {}).items()}
