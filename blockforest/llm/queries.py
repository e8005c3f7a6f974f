"""The queries of this subpackage by name, and their SQL where SQL can express them."""

from __future__ import annotations

from .decontaminate import OP6_SQL, op6_suffix_search
from .fingerprints import op7_weighted_sampling
from .language import op9_script_viterbi
from .licenses import op3_license_bands
from .near_dedup import op4_circulant_minhash
from .pieces import op10_unigram_pieces
from .quality import op1_bradley_terry
from .secrets import op2_random_field
from .suffix_dedup import op5_induced_suffix_array
from .token_counts import op8_pretoken_counts

QUERIES = {
    "op1_bradley_terry": op1_bradley_terry,
    "op2_random_field": op2_random_field,
    "op3_license_bands": op3_license_bands,
    "op4_circulant_minhash": op4_circulant_minhash,
    "op5_induced_suffix_array": op5_induced_suffix_array,
    "op6_suffix_search": op6_suffix_search,
    "op7_weighted_sampling": op7_weighted_sampling,
    "op8_pretoken_counts": op8_pretoken_counts,
    "op9_script_viterbi": op9_script_viterbi,
    "op10_unigram_pieces": op10_unigram_pieces,
}
ORACLES: dict[str, str] = {
    "op6_suffix_search": OP6_SQL,
}
