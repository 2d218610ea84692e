"""A corpus pipeline of five stages over ``documents``.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before it kept; ``run`` writes a stage's rows as
Parquet in the shared folder and reads them again for the next. All but the last return the columns of ``documents``.
SQL cannot express the learned stages, so ``ORACLE_SQL`` is None and the tests hold ``run`` against brute force.

Odd input: see the operators. A row without doc_id passes the stages like any other; repeated rows are near duplicates of
each other, so one of them stays; an empty table stays empty; extra columns of any name are kept by every stage but the last.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tuplegraph.llm import bpe, decontam, near_dup, pii, toxicity
from tuplegraph.llm.common import shared_dir, table
from tuplegraph.llm.queries import tokenizer_path


def _packed(docs: DataFrame) -> DataFrame:
    """doc_id, text and, as one struct, all other columns, whose names so never meet those of a stage."""
    others = [F.col(c) for c in docs.columns if c not in ("doc_id", "text")]
    return docs.select("doc_id", "text", *([F.struct(*others).alias("carried")] if others else []))


def _unpacked(docs: DataFrame, columns: list[str]) -> DataFrame:
    return docs.select(*[F.col(c) if c in ("doc_id", "text") else F.col("carried").getField(c).alias(c) for c in columns])


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is below one half. The lexicon is learned outside the held-out fold."""
    lexicon, weights = toxicity.held_out_model(docs.select("doc_id", "text"), table(spark, sf_dir, "labels"))
    return _unpacked(toxicity.score(_packed(docs), lexicon, weights).where("predicted = 0"), docs.columns)


#: Stands for a missing id in joins.
NO_ID = -(2**63)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates, the one with the least doc_id; documents without words all stay, and
    rows that are equal in id and text count as one."""
    kept = near_dup.link(docs.select("doc_id", "text")).where("kept").select(F.coalesce("doc_id", F.lit(NO_ID)).alias("id"), "th", "class_id")
    grouped = kept.where("class_id is not null").groupBy("class_id").agg(F.min(F.struct("id", "th")).alias("k")).select("k.id", "k.th")
    chosen = grouped.union(kept.where("class_id is null").select("id", "th").distinct())
    keyed = _packed(docs).withColumn("id", F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID))).withColumn("th", F.xxhash64("text"))
    # rows that are equal in id and text are chosen together; the join has dealt them alike, so one is kept without a shuffle
    return _unpacked(keyed.join(chosen, ["id", "th"], "left_semi").dropDuplicates(["id", "th"]), docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that overlap with no benchmark item."""
    return _unpacked(decontam.clean(_packed(docs), table(spark, sf_dir, "benchmark")), docs.columns)


def redact_personal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with personal data replaced by the name of its kind; ``n_chars`` follows the new text."""
    done = _unpacked(pii.redact(pii.find(_packed(docs))), docs.columns)
    return done.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else done


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, lang, source, text, n_tokens, and digests of the token ids and of the text that they decode to."""
    done = bpe.encode(docs, tokenizer_path())
    ids = F.concat_ws(",", F.col("ids").cast("array<string>"))
    return done.select("doc_id", "lang", "source", "text", "n_tokens", F.sha2(ids, 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("personal_data", redact_personal),
    ("bpe", encode_tokens),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    base = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for number, (name, stage) in enumerate(STAGES):
        at = f"{base}/{number}-{name}"
        stage(spark, docs, sf_dir).write.parquet(at)
        docs = spark.read.parquet(at)
    return docs
