"""The queries of the ten operators, and the SQL of those that SQL can express."""

from __future__ import annotations

from .bpe import op2_byte_pair_codec
from .counts import op4_token_counts
from .jaccard import ORACLE as OP6_SQL
from .jaccard import op6_jaccard_join
from .media import op9_media_chunks
from .mixing import op8_mixing_sources
from .scoring import op5_lm_scoring
from .sharding import op10_sharding
from .substrings import ORACLE as OP7_SQL
from .substrings import op7_substring_dedup
from .topk import ORACLE as OP3_SQL
from .topk import op3_exact_top_k
from .toxicity import op1_toxicity

QUERIES = {f.__name__: f for f in (op1_toxicity, op2_byte_pair_codec, op3_exact_top_k, op4_token_counts, op5_lm_scoring, op6_jaccard_join, op7_substring_dedup, op8_mixing_sources, op9_media_chunks, op10_sharding)}
ORACLES: dict[str, str] = {"op3_exact_top_k": OP3_SQL, "op6_jaccard_join": OP6_SQL, "op7_substring_dedup": OP7_SQL}
