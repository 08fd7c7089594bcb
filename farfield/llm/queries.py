"""The operators' queries over their whole tables, and SQL for those that SQL can express."""

from __future__ import annotations

from farfield.llm import ann, bpe, html, line_dedup, mixing, pii, sharding, simhash, topk, toxicity
from farfield.llm.common import table

QUERIES = {
    "op1_toxicity": lambda s, d: toxicity.op1_toxicity(table(s, d, "documents"), table(s, d, "labels")),
    "op2_line_dedup": lambda s, d: line_dedup.op2_line_dedup(table(s, d, "documents")),
    "op3_simhash": lambda s, d: simhash.op3_simhash(table(s, d, "documents")),
    "op4_multi_index": lambda s, d: ann.op4_multi_index(table(s, d, "embeddings")),
    "op5_mixing": lambda s, d: mixing.op5_mixing(table(s, d, "documents")),
    "op6_label_propagation": lambda s, d: sharding.op6_label_propagation(table(s, d, "documents")),
    "op7_norm_buckets": lambda s, d: topk.op7_norm_buckets(table(s, d, "embeddings")),
    "op8_bpe": lambda s, d: bpe.op8_bpe(table(s, d, "documents")),
    "op9_pii": lambda s, d: pii.op9_pii(table(s, d, "documents")),
    "op10_html": lambda s, d: html.op10_html(table(s, d, "pages")),
}

ORACLES = {"op2_line_dedup": line_dedup.ORACLE_SQL, "op7_norm_buckets": topk.ORACLE_SQL}
