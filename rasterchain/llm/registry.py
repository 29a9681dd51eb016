"""Queries of this subpackage, and the SQL that checks them where SQL can."""

from __future__ import annotations

from rasterchain.llm.html_extract import op9_html_extraction
from rasterchain.llm.license_scan import op10_license_scan
from rasterchain.llm.lm_score import op5_lm_scoring
from rasterchain.llm.mixing import OP8_SQL, op8_mixing
from rasterchain.llm.multi_index import OP1_SQL, op1_embedding_dedup
from rasterchain.llm.quality import OP3_SQL, op3_quality
from rasterchain.llm.sentencepiece_codec import op4_sentencepiece
from rasterchain.llm.simhash import op7_simhash
from rasterchain.llm.suffix_dedup import OP6_SQL, op6_suffix_dedup
from rasterchain.llm.url_filter import OP2_SQL, op2_url_filter

QUERIES = {
    "op1_embedding_dedup": op1_embedding_dedup,
    "op2_url_filter": op2_url_filter,
    "op3_quality": op3_quality,
    "op4_sentencepiece": op4_sentencepiece,
    "op5_lm_scoring": op5_lm_scoring,
    "op6_suffix_dedup": op6_suffix_dedup,
    "op7_simhash": op7_simhash,
    "op8_mixing": op8_mixing,
    "op9_html_extraction": op9_html_extraction,
    "op10_license_scan": op10_license_scan,
}
ORACLES: dict[str, str] = {"op1_embedding_dedup": OP1_SQL, "op2_url_filter": OP2_SQL, "op3_quality": OP3_SQL, "op6_suffix_dedup": OP6_SQL, "op8_mixing": OP8_SQL}
