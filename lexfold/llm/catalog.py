"""The operators' queries by name, and DuckDB SQL where it can express them."""

from __future__ import annotations

from .bpe_codec import op4_byte_bpe
from .decontamination import op6_decontamination
from .language_id import op8_language_id
from .line_dedup import op5_line_dedup
from .ngram_join import op1_ngram_jaccard
from .quality_classifier import op2_quality_classifier
from .quality_rules import op9_quality_rules
from .secret_scan import op10_secret_scan
from .token_store import op3_token_store
from .warc import OP7_SQL, op7_warc

QUERIES = {
    "op2_quality_classifier": op2_quality_classifier,
    "op7_warc": op7_warc,
    "op8_language_id": op8_language_id,
    "op10_secret_scan": op10_secret_scan,
    "op6_decontamination": op6_decontamination,
    "op3_token_store": op3_token_store,
    "op4_byte_bpe": op4_byte_bpe,
    "op1_ngram_jaccard": op1_ngram_jaccard,
    "op5_line_dedup": op5_line_dedup,
    "op9_quality_rules": op9_quality_rules,
}
ORACLE: dict[str, str] = {"op7_warc": OP7_SQL}
