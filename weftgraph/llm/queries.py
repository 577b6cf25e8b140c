"""Registered queries of the corpus operators and the SQL of those that SQL can express."""

from __future__ import annotations

from .backoff import OP5_SQL, op5_stupid_backoff
from .bpe import op6_bpe_roundtrip
from .langid import op7_crf_language
from .neighbours import op3_multiprobe_neighbours
from .packing import op9_best_fit_packing
from .quality import op10_quality_trees
from .sharding import OP4_SQL, op4_byte_sharding
from .simhash import op2_simhash_near_duplicates
from .substrings import op8_fm_index_removal
from .tiff import op1_tiff_media

QUERIES = {
    "op1_tiff_media": op1_tiff_media,
    "op2_simhash_near_duplicates": op2_simhash_near_duplicates,
    "op3_multiprobe_neighbours": op3_multiprobe_neighbours,
    "op4_byte_sharding": op4_byte_sharding,
    "op5_stupid_backoff": op5_stupid_backoff,
    "op6_bpe_roundtrip": op6_bpe_roundtrip,
    "op7_crf_language": op7_crf_language,
    "op8_fm_index_removal": op8_fm_index_removal,
    "op9_best_fit_packing": op9_best_fit_packing,
    "op10_quality_trees": op10_quality_trees,
}

ORACLES = {"op4_byte_sharding": OP4_SQL, "op5_stupid_backoff": OP5_SQL}
