"""The queries of this subpackage, by name, and the SQL of those that SQL can express."""

from .embeddings import op8_embedding_near_dedup
from .near_duplicates import op10_near_duplicates
from .oracles import ORACLE_SQL  # noqa: F401
from .order_minhash import op9_order_minhash
from .packing import op7_best_fit_packing
from .passages import op3_substring_dedup
from .secrets import op2_secret_scan
from .segmentations import op6_sampled_segmentations
from .toxicity import op1_toxicity
from .urls import op4_url_filter
from .warc import op5_warc_round_trip

QUERIES = {
    "op1_toxicity": op1_toxicity,
    "op2_secret_scan": op2_secret_scan,
    "op3_substring_dedup": op3_substring_dedup,
    "op4_url_filter": op4_url_filter,
    "op5_warc_round_trip": op5_warc_round_trip,
    "op6_sampled_segmentations": op6_sampled_segmentations,
    "op7_best_fit_packing": op7_best_fit_packing,
    "op8_embedding_near_dedup": op8_embedding_near_dedup,
    "op9_order_minhash": op9_order_minhash,
    "op10_near_duplicates": op10_near_duplicates,
}
