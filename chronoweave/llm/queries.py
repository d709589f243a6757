"""Queries and SQL of the training-data operators."""

from __future__ import annotations

from .bpe import op2_bpe
from .langid import op7_language
from .mixing import op1_mixture
from .neardup import OP4_SQL, op4_neardup
from .pii import op6_pii
from .quality import OP9_SQL, op9_quality
from .sharding import op8_sharding
from .spans import op5_substrings
from .tokenfile import op3_tokens
from .topk import OP10_SQL, op10_topk

QUERIES = {f.__name__: f for f in (op1_mixture, op2_bpe, op3_tokens, op4_neardup, op5_substrings, op6_pii, op7_language, op8_sharding, op9_quality, op10_topk)}
ORACLES = {"op4_neardup": OP4_SQL, "op9_quality": OP9_SQL, "op10_topk": OP10_SQL}
