"""Corpus preparation in stages, each by one operator of the subpackage llm; every stage reads what its predecessor wrote.

Defined results: documents with a null or empty text are never toxic, duplicate or contaminated, hold no secret and have no ids, so they stay; repeated
rows of one doc_id are decided on alike, except that near-duplicate removal keeps all rows of a doc_id that stays; a null doc_id stays unless
its text is near another document's; an empty table gives an empty result. All columns but ``text`` pass through unchanged, whatever their names
(``n_chars``, where present, follows the redacted text); in the last stage an input column named like one of its results is replaced.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxrec.llm import bpe, decontaminate, neardup, secrets, toxicity
from proxrec.llm.common import ensure_checkpoint_dir, load

OWN = ("doc_id", "text")


def shielded(docs: DataFrame, apply: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Applies an operator while the columns that it does not read go by names that it cannot write."""
    aside = {c: c if c in OWN else f"_passed_{i}" for i, c in enumerate(docs.columns)}
    done = apply(docs.select(*[F.col(f"`{c}`").alias(a) for c, a in aside.items()]))
    return done.select(*[F.col(a).alias(c) for c, a in aside.items()])


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose probability of being toxic reaches the model's cut go."""
    model = toxicity.train(docs, load(spark, sf_dir, "labels"))
    return shielded(docs, lambda d: toxicity.score(d, model).where("NOT toxic"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of links at 80 % or more stays: the one with the smallest id."""
    return shielded(docs, lambda d: neardup.survivors(d, percent=80))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go."""
    return shielded(docs, lambda d: decontaminate.decontaminate(d, load(spark, sf_dir, "benchmark")).where("n_hit = 0"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by a mark and n_chars follows; no document goes."""
    length = next((f"_passed_{i}" for i, c in enumerate(docs.columns) if c == "n_chars"), None)

    def redacted(d: DataFrame) -> DataFrame:
        found = secrets.redact(secrets.scan(d))
        return found.withColumn(length, F.when(F.size("secrets") > 0, F.length("text").cast("long")).otherwise(F.col(length))) if length else found

    return shielded(docs, redacted)


def encode_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The ids of every text, and digests that show the round trip through decoding; the text itself is left out."""
    new = {
        "n_tokens": F.size("ids").cast("long"),
        "ids": F.col("ids"),
        "ids_sha256": F.sha2(F.concat_ws(",", F.col("ids").cast("array<string>")).cast("binary"), 256),
        "decoded_sha256": F.sha2("decoded", 256),
    }
    passed = {c: f"_passed_{i}" for i, c in enumerate(docs.columns) if c != "text" and c.lower() not in new}
    vocabulary = bpe.public_vocabulary()
    plain = docs.select("text", *[F.col(f"`{c}`").alias(a) for c, a in passed.items()])
    coded = bpe.decode(bpe.encode(plain, vocabulary, keep=list(passed.values())), vocabulary)
    return coded.select(*[F.col(a).alias(c) for c, a in passed.items()], *[x.alias(name) for name, x in new.items()])


STAGES = [
    ("toxicity", drop_toxic),
    ("near-dedup", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("secrets", redact_secrets),
    ("encoding", encode_tokens),
]

#: The toxicity model and the encoding have no SQL form; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result is written to the shared checkpoint folder and read again, and goes once the next one is written."""
    ensure_checkpoint_dir(spark)
    top = f"{spark.sparkContext.getCheckpointDir()}/corpus-{uuid.uuid4().hex}"
    docs = load(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{top}/{k}")
        docs = spark.read.parquet(f"{top}/{k}")
        if k:
            old = spark._jvm.org.apache.hadoop.fs.Path(f"{top}/{k - 1}")
            old.getFileSystem(spark._jsc.hadoopConfiguration()).delete(old, True)
    return docs
