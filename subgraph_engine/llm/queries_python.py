"""Queries of the operators that use Python on the executors."""

from __future__ import annotations

from subgraph_engine.llm import bpe, html_text, license_scan, minhash, planes, topk, toxicity

QUERIES = {
    "op1_topk": topk.op1,
    "op3_minhash": minhash.op3,
    "op4_html": html_text.texts_of_pages,
    "op5_bpe": bpe.digests_of_documents,
    "op6_toxicity": toxicity.scores_of_documents,
    "op7_licenses": license_scan.licenses_of_documents,
    "op10_planes": planes.files_of_documents,
}

ORACLE_SQL = {"op1_topk": topk.ORACLE, "op3_minhash": minhash.ORACLE}
