"""Queries of this subpackage for ``__spark_entry__``; SQL twins where SQL can express them."""

from __future__ import annotations

from .embeddings import op3_grid_order_join
from .minhash import op2_minhash_classes
from .mixing import OP4_SQL, op4_mix_sources
from .packing import op1_retrieval_packing
from .quality import BASE_SQL as QUALITY_SQL
from .quality import op8_robust_outliers, quality_base_rules
from .repair import op6_pair_grammar
from .secrets import BASE_SQL as SECRETS_SQL
from .secrets import op7_ownership_secrets, secret_base_counts
from .separators import op10_separator_scan
from .suffixes import op5_suffix_array_dedup
from .sharding import OP9_SQL, op9_byte_prefix_shards

QUERIES = {
    "op1_retrieval_packing": op1_retrieval_packing,
    "op2_minhash_classes": op2_minhash_classes,
    "op3_grid_order_join": op3_grid_order_join,
    "op4_mix_sources": op4_mix_sources,
    "op5_suffix_array_dedup": op5_suffix_array_dedup,
    "op6_pair_grammar": op6_pair_grammar,
    "op7_ownership_secrets": op7_ownership_secrets,
    "op8_robust_outliers": op8_robust_outliers,
    "op9_byte_prefix_shards": op9_byte_prefix_shards,
    "op10_separator_scan": op10_separator_scan,
    "quality_base_rules": quality_base_rules,
    "secret_base_counts": secret_base_counts,
}

ORACLES: dict[str, str] = {
    "op4_mix_sources": OP4_SQL,
    "op9_byte_prefix_shards": OP9_SQL,
    "quality_base_rules": QUALITY_SQL,
    "secret_base_counts": SECRETS_SQL,
}
