"""Exact deduplication by most-significant-digit radix partitioning.

Documents are split by the first bytes of their normalised text, each group again by the bytes that follow, and so on: a row carries the
number of its group, and a round's digit is the next bytes alone. A group is finished when one document is left in it or when its
texts have ended. Digits widen geometrically, so a text of n bytes takes about log n rounds. Groups are told apart by the bytes
themselves: no digest decides equality.

Spread over a cluster: each round is one pre-aggregated count per group and digit (copies of any number are one row
per task), then a join of the crowded ones, with their new group numbers, back to the rows, which adaptive execution splits where
a group is large. Only rows whose hash bit is set among the crowded groups are shuffled. A round's survivors are written to the
shared folder, group numbers with them, so that a lost executor can't change them.

Defined results: a null text counts as empty, and all empty texts are equal to each other. A null key sorts after all
others. Among rows with the same key and text one is kept. Extra columns of any name
travel along under names of the operator's own. The input must be a deterministic plan, such as a table scan, since it is read more than once.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Bytes in the first digit, and how many times as many bytes all digits up to the next one have.
FIRST, WIDEN = 64, 16


def normalised(text: Column) -> Column:
    """White-space runs become one space; only runs other than a lone space are rewritten."""
    return F.regexp_replace(common.clean_text(text), r"[\x09-\x0D][ \x09-\x0D]*| [ \x09-\x0D]+", " ")


def digits(rows: DataFrame, text: Column, done: int, upto: int) -> DataFrame:
    """Adds digit, bytes `done` to `upto` of the normalised text; twice as much text is normalised, or all where that doesn't do."""
    some = rows.withColumn("some", normalised(F.substring(common.clean_text(text), 1, 2 * upto)).cast("binary"))
    enough = (F.octet_length("some") > upto) | (F.length(text) <= 2 * upto) | text.isNull()
    whole = F.when(enough, F.col("some")).otherwise(normalised(text).cast("binary"))
    return some.withColumn("digit", F.substring(whole, done + 1, upto - done)).drop("some")


def exact_groups(docs: DataFrame, text: str = "text", key: str = "doc_id", digest: bool = False, first: int = FIRST, widen: int = WIDEN) -> DataFrame:
    """One row per input row: its columns as p0, p1, ..., then keep_key, group_size, kept (and text_sha256).

    Columns that a caller drops afterwards are not shuffled.
    """
    kept_as = {c: f"p{i}" for i, c in enumerate(docs.columns)}
    words, who = F.col(kept_as[text]), F.col(kept_as[key])
    own = docs.select(*[common.col(c).alias(p) for c, p in kept_as.items()])
    rows = common.identified(own, kept_as[key], list(kept_as.values())).withColumnRenamed("uid", "rid").drop("ord")
    if digest:
        rows = rows.withColumn("text_sha256", F.sha2(normalised(words).cast("binary"), 256))
    carried = [c for c in rows.columns if c != "rid"]
    rows = rows.withColumn("g", F.lit(0).cast("long"))
    done, upto, out = 0, first, []
    while True:
        cut = digits(rows, words, done, upto).withColumn("at", F.xxhash64("g", "digit"))
        best = F.min(F.struct(who.isNull().alias("none"), who.alias("key"), F.col("rid").alias("rid")))
        groups = cut.groupBy("g", "digit").agg(F.count(F.lit(1)).alias("n"), best.alias("best"))
        crowded = groups.filter("n > 1").select(F.col("g").alias("g1"), F.col("digit").alias("d1"), "n", "best", F.monotonically_increasing_id().alias("g2"), F.xxhash64("g", "digit").alias("at"))
        crowded = common.stage(crowded, "radix-groups")
        # a row that is alone finds no crowded group; its own values stand for the group's
        met = (F.col("g") == F.col("g1")) & (F.col("digit") == F.col("d1"))
        alone = cut.drop("at").join(crowded.drop("at").hint("merge"), met, "left")
        out.append(
            alone.filter(F.col("n").isNull() | (F.length("d1") < upto - done)).select(
                *carried,
                F.when(F.col("n").isNull(), who).otherwise(F.col("best.key")).alias("keep_key"),
                F.coalesce("n", F.lit(1)).cast("long").alias("group_size"),
                F.coalesce(F.col("best.rid") == F.col("rid"), F.lit(True)).alias("kept"),
            )
        )
        open_groups = crowded.filter(F.length("d1") >= upto - done)
        if open_groups.isEmpty():
            break
        likely = common.sifted(cut, "at", common.sieve(open_groups, "at")).drop("at").join(open_groups.select("g1", "d1", "g2").hint("merge"), met)
        rows = common.stage(likely.select(*carried, "rid", F.col("g2").alias("g")), "radix-rows")
        common.sweep(docs.sparkSession)
        done, upto = upto, upto * widen
    whole = out[0]
    for more in out[1:]:
        whole = whole.union(more)
    names = [*kept_as.values(), "keep_key", "group_size", "kept", *(["text_sha256"] if digest else [])]
    return whole.select(*names)


def kept_documents(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """The rows that stay, with the columns of docs."""
    out = exact_groups(docs, text, key).filter("kept")
    return out.select(*[F.col(f"p{i}").alias(c) for i, c in enumerate(docs.columns)])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    got = exact_groups(docs, digest=True)
    return got.select(F.col("p0").alias("doc_id"), F.col("keep_key").alias("keep_id"), "group_size", "kept", "text_sha256")


SQL = r"""
WITH d AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS body FROM documents),
g AS (SELECT body, min(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY body)
SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(body) AS text_sha256
FROM d JOIN g USING (body)
"""
