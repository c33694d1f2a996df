"""Corpus pipeline: toxicity filter, near-duplicate removal, pseudonyms, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the
columns of documents. ``run`` writes each stage's rows to the shared folder and reads them again.
SQL cannot express the stages (a trained model, fingerprints, keyed digests, a tokenizer), so there is none; tests
hold them against brute force.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from nodeweave.llm import neardup, packing, pii, store, toxicity
from nodeweave.ship import ship


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the factorization machine doesn't reject; a null or empty text is judged as one without terms.

    Repeated rows are judged alike and all stay or all go. Other columns pass, whatever their names; no rows give none.
    """
    ship(spark)
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    columns = docs.columns
    return toxicity.score(docs, toxicity.train(docs, labels)).filter("predicted = 0").select(*columns)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near copies (five words, similarity 0.8): the one of least doc_id.

    Rows are judged one by one. Where doc_ids repeat, rows of one doc_id with unlike texts are documents of their
    own; of several rows with a group's least doc_id, the first in the table stays.
    """
    ship(spark)
    if not docs.groupBy("doc_id").count().filter("count > 1").limit(1).count():
        groups = neardup.near_groups(docs).filter(F.col("doc_id") != F.col("component_id")).select("doc_id")
        return docs.join(groups, "doc_id", "left_anti").select(*docs.columns)
    row = store.fresh(docs.columns, "__row")
    rows = store.materialize(docs.withColumn(row, F.monotonically_increasing_id()), "rows")  # written, so that a row keeps its number
    groups = neardup.near_groups(rows.select(F.col(row).alias("doc_id"), "text")).withColumnRenamed("doc_id", row)
    least = F.min(F.struct(F.col("doc_id").isNull(), "doc_id", row))
    kept = groups.join(rows.select(row, "doc_id"), row).groupBy("component_id").agg(least[row].alias(row)).select(row)
    return rows.join(kept, row, "left_semi").select(*docs.columns)


def pseudonymise(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, personal values replaced; n_chars follows the new text where there is such a column.

    A null text stays null. Repeated rows are changed alike. The key is the session's setting ``pii.KEY_SETTING``. Other
    columns pass, also those named n_values or kinds.
    """
    columns = docs.columns
    mine = {c: f"__own_{i}" for i, c in enumerate(columns) if c.lower() in ("n_values", "kinds")}
    out = pii.pseudonymise(docs.withColumnsRenamed(mine))
    if "n_chars" in columns:
        out = out.withColumn("n_chars", F.when(F.col("n_values") > 0, F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return out.drop("n_values", "kinds").withColumnsRenamed({v: k for k, v in mine.items()}).select(*[F.col(f"`{c}`") for c in columns])


#: Part of the encoder's memos that a worker fills here, where the executor's heap has grown in the stages before.
PACK_MEMO = 0.25


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of 2,048 ids; a null text is empty, and its end id a piece.

    Rows with one doc_id are documents of their own; equal pieces take their places in any order. Other columns are left out.
    """
    import public_tokenizers

    ship(spark)
    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.json"), memo=PACK_MEMO)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", drop_toxic),
    ("simhash_near_dedup", drop_copies),
    ("pii", pseudonymise),
    ("packing", pack),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages applied to documents, each written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = store.materialize(docs, f"stage-{name}")
    return docs
