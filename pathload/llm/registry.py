"""Queries and SQL of the training-data operators."""

from __future__ import annotations

from pathload.llm import bpe, forest, jaccard, kdtree, packing, runlength, secrets, toxicity, warc, windows

QUERIES = {
    "op1_runlength": runlength.op1_runlength,
    "op2_secrets": secrets.op2_secrets,
    "op3_kdtree": kdtree.op3_kdtree,
    "op4_jaccard": jaccard.op4_jaccard,
    "op5_forest": forest.op5_forest,
    "op6_packing": packing.op6_packing,
    "op7_bpe": bpe.op7_bpe,
    "op8_warc": warc.op8_warc,
    "op9_toxicity": toxicity.op9_toxicity,
    "op10_windows": windows.op10_windows,
}
ORACLES = {"op1_runlength": runlength.ORACLE, "op3_kdtree": kdtree.ORACLE, "op4_jaccard": jaccard.ORACLE, "op5_forest": forest.ORACLE, "op8_warc": warc.ORACLE, "op10_windows": windows.ORACLE}
