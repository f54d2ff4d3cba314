"""Queries of this subpackage and the SQL that checks them."""

from __future__ import annotations

from webtext.llm import q01, q02, q03, q04, q05, q06, q07, q08, q09, q10

QUERIES = {
    "op1_chat": q01.op1_chat,
    "op2_url_filter": q02.op2_url_filter,
    "op3_audio": q03.op3_audio,
    "op4_near_duplicates": q04.op4_near_duplicates,
    "op5_lm_score": q05.op5_lm_score,
    "op6_quality": q06.op6_quality,
    "op7_sharding": q07.op7_sharding,
    "op8_mixing": q08.op8_mixing,
    "op9_bpe": q09.op9_bpe,
    "op10_warc": q10.op10_warc,
}
ORACLES = {"op1_chat": q01.SQL, "op2_url_filter": q02.SQL, "op7_sharding": q07.SQL, "op10_warc": q10.SQL}
