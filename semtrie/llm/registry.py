"""Queries of the corpus operators, by contract name."""

from __future__ import annotations

from semtrie.llm import linededup, mixing, neardup, quality, secrets, segment, tokencount, vectors, warc


def queries() -> dict:
    return {
        "op1_warc_transactions": warc.op1_warc_transactions,
        "op2_quality_ranking": quality.op2_quality_ranking,
        "op3_vector_near_duplicates": vectors.op3_vector_near_duplicates,
        "op5_nearest_neighbours": vectors.op5_nearest_neighbours,
        "op4_near_duplicates": neardup.op4_near_duplicates,
        "op6_secret_scan": secrets.op6_secret_scan,
        "op7_line_dedup": linededup.op7_line_dedup,
        "op8_mix_sources": mixing.op8_mix_sources,
        "op10_sample_segmentations": segment.op10_sample_segmentations,
        "op9_token_counts": tokencount.op9_token_counts,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_warc_transactions": warc.OP1_SQL, "op3_vector_near_duplicates": vectors.OP3_SQL, "op4_near_duplicates": neardup.OP4_SQL, "op6_secret_scan": secrets.OP6_SQL, "op7_line_dedup": linededup.OP7_SQL}
