"""Queries of this subpackage by name, and their SQL where SQL can express them."""

from __future__ import annotations

from chronopath.llm import decontaminate, jaccard, lengths, linechunks, packing, quality, substrings, tiff, toxicity, warc


def queries() -> dict:
    import corpus_pipeline

    return {
        "pipeline": corpus_pipeline.run,
        "op1_decontaminate": decontaminate.op1_decontaminate,
        "op2_toxicity": toxicity.op2_toxicity,
        "op3_pack": packing.op3_pack,
        "op4_warc": warc.op4_warc,
        "op5_lengths": lengths.op5_lengths,
        "op6_jaccard": jaccard.op6_jaccard,
        "op7_tiff": tiff.op7_tiff,
        "op8_substrings": substrings.op8_substrings,
        "op9_lines": linechunks.op9_lines,
        "op10_quality": quality.op10_quality,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op4_warc": warc.OP4_SQL,
        "op8_substrings": substrings.OP8_SQL,
        "op9_lines": linechunks.OP9_SQL,
    }
