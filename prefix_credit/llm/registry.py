"""The queries of this subpackage for the driver, and their SQL where SQL can express them."""

from __future__ import annotations

from . import chat_format, licenses, near_dup, packing, sharding
from .ann import op3_ivf_pq_search
from .chat_format import op6_preference_format
from .context_mixing import op5_context_mixing_score
from .decontaminate import op1_cgk_decontamination
from .html_text import op10_html_main_text
from .licenses import op8_license_scan
from .near_dup import op7_minhash_near_dedup
from .packing import op9_length_bucket_packing
from .sharding import op2_hilbert_sharding
from .toxicity import op4_ordinal_toxicity

QUERIES = {f.__name__: f for f in (op1_cgk_decontamination, op2_hilbert_sharding, op3_ivf_pq_search, op4_ordinal_toxicity, op5_context_mixing_score, op6_preference_format, op7_minhash_near_dedup, op8_license_scan, op9_length_bucket_packing, op10_html_main_text)}
ORACLES: dict[str, str] = {"op2_hilbert_sharding": sharding.oracle(), "op6_preference_format": chat_format.ORACLE, "op7_minhash_near_dedup": near_dup.ORACLE, "op8_license_scan": licenses.oracle(), "op9_length_bucket_packing": packing.oracle()}
