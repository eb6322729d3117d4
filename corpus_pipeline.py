"""A training-data pipeline over ``documents``: toxicity, near-duplicates, repeated strings, packing.

Each stage takes (spark, docs, sf_dir), works on all rows of its predecessor and, but for the last, returns the
columns of documents.  ``run`` writes each stage's rows as Parquet in the shared folder and reads them again, so
a lost executor costs at most one stage.

Edge cases: rows with a null doc_id are not comparable as duplicates and stay; of rows with equal ids in one group
the one of least row hash stays, rows of equal ids in different groups all stay; a text that consists of repeated
strings only stays as an empty one; further columns may have any name and come through; empty tables give no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from private_distinct.llm import bpe, near_copies, packing, suffix_dedup, toxicity
from private_distinct.llm.common import materialise

THRESHOLD, SEQUENCE, LENGTH = 0.5, 2048, 50
VOCABULARY, TOKENIZER = "byte_bpe_50k.tiktoken", "byte_bpe_50k.json"


def _renamed(docs: DataFrame) -> DataFrame:
    """Columns other than doc_id and text as c0, c1, ..., which clash with no operator's own."""
    return docs.select("doc_id", "text", *[F.col(c).alias(f"c{i}") for i, c in enumerate(docs.columns) if c not in ("doc_id", "text")])


def _restored(rows: DataFrame, names: list[str]) -> DataFrame:
    return rows.select(*[F.col(c if c in ("doc_id", "text") else f"c{i}").alias(c) for i, c in enumerate(names)])


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose whole text scores under the threshold."""
    usable = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != 0
    network = toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"), usable)
    rows = _renamed(docs)
    return _restored(toxicity.score(rows, network, rows.columns).where(F.col("score") < THRESHOLD), docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The row of least id of each group linked by five-word similarity of 0.8 or more: by SimHash, then exactly."""
    known = docs.where("doc_id is not null")
    row = [F.col("doc_id"), F.xxhash64(*docs.columns).alias("_tie")]
    groups = near_copies.groups(known)
    rows = known.select(*row, near_copies.text_hash("text").alias("th")).join(groups, "th")
    rows = materialise(rows.groupBy("root", "doc_id", "_tie").agg(F.count(F.lit(1)).alias("n")), "copy-rows")
    first = rows.groupBy("root").agg(F.min(F.struct("doc_id", "_tie")).alias("x")).select("root", "x.*")
    same = [rows[c] == first[c] for c in ("root", "doc_id", "_tie")]
    gone = materialise(rows.join(first, same, "left_anti").select("doc_id", "_tie").distinct(), "copies-gone")
    again = materialise(rows.where("n > 1").join(first, same, "left_semi").select("doc_id", "_tie"), "rows-again")
    kept = known.select("*", row[1]).join(gone, ["doc_id", "_tie"], "left_anti")
    if not again.isEmpty():  # rows that are equal in every column stay once
        once = kept.join(again, ["doc_id", "_tie"], "left_semi").dropDuplicates(["doc_id", "_tie"])
        kept = kept.join(again, ["doc_id", "_tie"], "left_anti").union(once)
    return kept.select(*docs.columns).union(docs.where("doc_id is null"))


def drop_repeated_strings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the bytes of strings that an earlier document has."""
    rows = _renamed(docs)
    others = [c for c in rows.columns if c != "text"]
    left = suffix_dedup.remove(rows, others, length=LENGTH, as_text=True).withColumn("text", F.col("kept_text"))
    out = _restored(left, docs.columns)
    return out.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else out


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Where each piece of each document goes in sequences of 2048 tokens."""
    import public_tokenizers

    ranks = bpe.read_ranks(public_tokenizers.path(VOCABULARY))
    special = packing.special_tokens(public_tokenizers.path(TOKENIZER))
    return packing.pack(packing.encode_pieces(docs, ranks, public_tokenizers.PATTERN, SEQUENCE, special=special), SEQUENCE)


STAGES = [
    ("toxicity", drop_toxic),
    ("simhash_near_dedup", drop_near_copies),
    ("suffix_array_dedup", drop_repeated_strings),
    ("best_fit_packing", pack_sequences),
]

#: The stages train a network and link by fingerprints, which SQL cannot express; tested against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return docs


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict:
    return {}
