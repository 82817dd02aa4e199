"""Registry of the training-data queries and of their SQL."""

from __future__ import annotations

from .exact_dedup import OP10_SQL, op10_exact_dedup
from .line_dedup import OP9_SQL, op9_line_dedup
from .media import op5_media
from .mixing import OP8_SQL, op8_mixing
from .ngram_join import op7_ngram_join
from .packing import op2_packing
from .pii import op3_pii
from .quality import op6_quality
from .substring_dedup import op1_suffix_dedup
from .url_filter import OP4_SQL, op4_url_filter

QUERIES = {
    "op1_suffix_dedup": op1_suffix_dedup,
    "op2_packing": op2_packing,
    "op3_pii": op3_pii,
    "op4_url_filter": op4_url_filter,
    "op5_media": op5_media,
    "op6_quality": op6_quality,
    "op7_ngram_join": op7_ngram_join,
    "op8_mixing": op8_mixing,
    "op9_line_dedup": op9_line_dedup,
    "op10_exact_dedup": op10_exact_dedup,
}

ORACLE_SQL = {
    "op4_url_filter": OP4_SQL,
    "op8_mixing": OP8_SQL,
    "op9_line_dedup": OP9_SQL,
    "op10_exact_dedup": OP10_SQL,
}
