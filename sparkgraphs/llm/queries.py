"""The registered corpus queries and their SQL."""

from __future__ import annotations

from . import bpe_codec, decontaminate, embedding_dedup, language_id, line_dedup, ngram_join, surrogates, token_counts, toxicity, warc


def queries() -> dict:
    found = (
        embedding_dedup.op1_embedding_near_dedup,
        token_counts.op2_token_counts, warc.op4_warc_revisits, toxicity.op5_toxicity, decontaminate.op6_decontaminate,
        line_dedup.op7_line_dedup, bpe_codec.op8_bpe_encode_decode, language_id.op9_language_id,
        surrogates.op10_surrogates, ngram_join.op3_ngram_jaccard,
    )
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {"op1_embedding_near_dedup": embedding_dedup.OP1_SQL, "op4_warc_revisits": warc.OP4_SQL, "op7_line_dedup": line_dedup.OP7_SQL}
