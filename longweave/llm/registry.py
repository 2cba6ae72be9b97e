"""The queries of this subpackage and, where SQL can express them, their SQL."""

from __future__ import annotations

from longweave.llm import binary, decontaminate, hnsw, line_dedup, near_dup, packing, pii, quality, secrets, warc

QUERIES = {
    "op1_near_dup": near_dup.op1_near_dup,
    "op2_secrets": secrets.op2_secrets,
    "op3_hnsw": hnsw.op3_hnsw,
    "op4_warc": warc.op4_warc,
    "op5_packing": packing.op5_packing,
    "op6_line_dedup": line_dedup.op6_line_dedup,
    "op7_pii": pii.op7_pii,
    "op8_quality": quality.op8_quality,
    "op9_decontaminate": decontaminate.op9_decontaminate,
    "op10_token_binary": binary.op10_token_binary,
}
ORACLES = {"op1_near_dup": near_dup.SQL, "op4_warc": warc.SQL, "op6_line_dedup": line_dedup.SQL}
