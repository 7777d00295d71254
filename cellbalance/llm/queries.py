"""Queries of the training-data operators, by name, and their SQL where SQL can express them."""

from __future__ import annotations

from . import oracle
from .decontamination import op5_suffix_array_decontamination
from .language_model import op10_kneser_ney_scores
from .line_dedup import op7_simhash_line_dedup
from .ngram_join import op6_prefix_tree_join
from .packing import op9_sum_of_squares_packing
from .quality_classifier import op8_kneser_ney_quality
from .quality_rules import op1_ngram_likelihood_rules
from .secrets import op3_markov_secret_scan
from .sharding import op2_karmarkar_karp_sharding
from .substring_dedup import op4_fm_index_substring_dedup

QUERIES = {f.__name__: f for f in (op1_ngram_likelihood_rules, op2_karmarkar_karp_sharding, op3_markov_secret_scan, op4_fm_index_substring_dedup, op5_suffix_array_decontamination, op6_prefix_tree_join, op7_simhash_line_dedup, op8_kneser_ney_quality, op9_sum_of_squares_packing, op10_kneser_ney_scores)}
ORACLE_SQL: dict[str, str] = {
    "op4_fm_index_substring_dedup": oracle.repeated_windows(),
    "op5_suffix_array_decontamination": oracle.benchmark_windows(),
    "op6_prefix_tree_join": oracle.similar_sets(),
}
