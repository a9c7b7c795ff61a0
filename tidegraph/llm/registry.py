"""The queries of this subpackage and their SQL, for __spark_entry__.py."""

from __future__ import annotations

from tidegraph.llm import op1, op2, op3, op4, op5, op6, op7, op8, op9, op10, pipeline

QUERIES = {
    "pipeline": pipeline.run,
    "op1_personal_data": op1.query,
    "op2_near_duplicates": op2.query,
    "op3_lm_scoring": op3.query,
    "op4_document_fingerprints": op4.query,
    "op5_top_k": op5.query,
    "op6_toxicity": op6.query,
    "op7_mixing": op7.query,
    "op8_quality": op8.query,
    "op9_pieces": op9.query,
    "op10_language_id": op10.query,
}

SQL = {"op2_near_duplicates": op2.SQL,
    "op5_top_k": op5.SQL,
    "op7_mixing": op7.SQL}
