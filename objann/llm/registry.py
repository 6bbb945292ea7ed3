"""The queries of this subpackage and their SQL, for __spark_entry__.py."""

from __future__ import annotations

from objann.llm.bpe_codec import op2_bpe_codec
from objann.llm.html_extract import op10_html_extract
from objann.llm.media_chunks import op7_media_chunks
from objann.llm.near_join import op1_near_join
from objann.llm.packing import op4_packing
from objann.llm.pii import op3_pii
from objann.llm.token_counts import op6_token_counts
from objann.llm.topk_search import OP5_SQL, op5_topk
from objann.llm.toxicity import op9_toxicity
from objann.llm.url_filter import OP8_SQL, op8_url_filter

QUERIES = {
    "op1_near_join": op1_near_join,
    "op2_bpe_codec": op2_bpe_codec,
    "op3_pii": op3_pii,
    "op4_packing": op4_packing,
    "op5_topk": op5_topk,
    "op6_token_counts": op6_token_counts,
    "op7_media_chunks": op7_media_chunks,
    "op8_url_filter": op8_url_filter,
    "op9_toxicity": op9_toxicity,
    "op10_html_extract": op10_html_extract,
}

ORACLES: dict[str, str] = {"op5_topk": OP5_SQL, "op8_url_filter": OP8_SQL}
