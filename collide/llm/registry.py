"""Queries of this subpackage and the SQL that gives the same rows."""

from __future__ import annotations

from . import oracle_sql
from .bm25_search import op6_bm25_topk
from .jaccard_join import op7_jaccard_join
from .line_dedup import op2_line_dedup
from .neighbour_classifier import op10_quality_classifier
from .packing import op9_packing
from .quality_rules import op3_quality_rules
from .secret_scan import op1_secret_scan
from .sentencepiece_codec import op4_sentencepiece
from .substring_dedup import op8_substring_dedup
from .suffix_dedup import op5_suffix_dedup

QUERIES = {
    f.__name__: f
    for f in (op1_secret_scan, op2_line_dedup, op3_quality_rules, op4_sentencepiece, op5_suffix_dedup, op6_bm25_topk, op7_jaccard_join, op8_substring_dedup, op9_packing, op10_quality_classifier)
}

#: The others have no SQL; tests hold them against brute force, an exact round trip or held-out labels.
ORACLE_SQL: dict[str, str] = oracle_sql.SQL
