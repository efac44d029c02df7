"""The corpus pipeline: documents are filtered, deduplicated, decontaminated and tokenised, stage by stage.

Each stage works on all that its predecessor kept, and is written before the next one reads it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkgraphs.llm.bpe_codec import encode_decode
from sparkgraphs.llm.common import Stages, table
from sparkgraphs.llm.decontaminate import drop_contaminated
from sparkgraphs.llm.line_dedup import dedup_lines
from sparkgraphs.llm.ngram_join import keep_one_of_each
from sparkgraphs.llm.toxicity import fit_field, fit_rows, score_toxicity


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents predicted toxic go."""
    model = fit_field(*fit_rows(docs, table(spark, sf_dir, "labels")))
    return score_toxicity(docs, model, spans=False).where("predicted = 0").select(*docs.columns)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that many documents share stay in one of them; n_chars follows the text."""
    kept = dedup_lines(docs)
    return kept.select(*[F.char_length("text").cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else F.col(c) for c in docs.columns])


def ngram_jaccard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by five-word shingles at 0.8 the one with the smallest doc_id stays."""
    return keep_one_of_each(docs, n=5, percent=80)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark passage go."""
    return drop_contaminated(docs, table(spark, sf_dir, "benchmark"))


def bpe_encode_decode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Adds the ids, their number, and whether decoding gives the text back."""
    import public_tokenizers

    out = encode_decode(docs, public_tokenizers.path("byte_bpe_50k.json"))
    return out.withColumns({"n_tokens": F.size("bpe_ids").cast("long"), "round_trip": F.col("bpe_text") == F.coalesce("text", F.lit(""))}).drop("bpe_text")


STAGES = [(f.__name__, f) for f in (toxicity, line_dedup, ngram_jaccard, decontamination, bpe_encode_decode)]
#: The first and the last stage have no SQL form.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    written = Stages(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        docs = written.keep(stage(spark, docs, sf_dir))
    return docs
