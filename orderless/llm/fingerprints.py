"""Document fingerprints: a Merkle tree over sections and paragraphs, in built-in functions only.

A text's sections are its lines; a section's paragraphs are its sentences, cut at `PIECE` code points. A leaf is the SHA-256 of its
paragraph, a section's node the SHA-256 of its leaves, the root the SHA-256 of the sections' nodes: equal roots mean equal texts. The
fingerprint string holds the root whole, 16 hex digits of each section's node and 8 of each leaf, some three tenths of the text's
length, so that two fingerprints can be compared without the texts, from the root down: equal roots end the comparison; sections with
equal nodes agree as a whole; only the leaves of the other sections are compared.

Likeness is twice what agrees over all: leaves of the sections in both (each different section once) and, of the other sections, the
different leaves. The sections where two texts differ, by number, locate edits.

Defined results: a null text is empty; an empty text has one section without leaves; two empty texts have likeness 1. The successor
of a document is the one with the next smaller id, of the smallest the largest; rows with equal ids follow each other in
any one order, null ids come first. Very long texts only lengthen their own row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

PIECE = 32


def tree(text: Column) -> Column:
    """Sections of a text in order: arrays of struct(node, leaves), hashes in lowercase hex."""
    pattern = F.lit(rf"[^.!?]{{1,{PIECE}}}[.!?]*|[.!?]+")
    leaves = F.transform(F.split(text, "\n", -1), lambda s: F.transform(F.regexp_extract_all(s, pattern, F.lit(0)), lambda p: F.sha2(p.cast("binary"), 256)))
    return F.transform(leaves, lambda x: F.struct(F.sha2(F.concat_ws(",", x).cast("binary"), 256).alias("node"), x.alias("leaves")))


def fingerprint(sections: Column) -> Column:
    """root|node:leaf,leaf;node:... of a tree."""
    root = F.sha2(F.concat_ws(",", F.transform(sections, lambda s: s["node"])).cast("binary"), 256)
    told = F.transform(sections, lambda s: F.concat(F.substring(s["node"], 1, 16), F.lit(":"), F.concat_ws(",", F.transform(s["leaves"], lambda x: F.substring(x, 1, 8)))))
    return F.concat(root, F.lit("|"), F.concat_ws(";", told))


def sections(print_: Column) -> Column:
    """The sections a fingerprint tells: arrays of "node:leaf,leaf"."""
    return F.split(F.substring_index(print_, "|", -1), ";")


def leaves_of(some: Column) -> Column:
    """The leaves of sections, in order."""
    return F.flatten(F.transform(some, lambda s: F.filter(F.split(F.substring_index(s, ":", -1), ","), lambda x: x != "")))


def likeness(a: Column, b: Column) -> Column:
    """How much two arrays of sections agree, 0 to 1, from the sections' nodes down to the leaves of those that only one has."""
    both = F.size(leaves_of(F.array_intersect(a, b)))
    x, y = (F.array_distinct(leaves_of(F.array_except(p, q))) for p, q in ((a, b), (b, a)))
    total = 2 * both + F.size(x) + F.size(y)
    return F.when(a == b, F.lit(1.0)).when(total == 0, F.lit(0.0)).otherwise(2.0 * (both + F.size(F.array_intersect(x, y))) / total)


def changed_sections(a: Column, b: Column) -> Column:
    """Numbers of sections (from 0) whose nodes differ between two arrays of sections."""
    pairs = F.arrays_zip(a.alias("a"), b.alias("b"))
    marked = F.transform(pairs, lambda x, i: F.when(x["a"].eqNullSafe(x["b"]), F.lit(-1)).otherwise(i))
    return F.filter(marked, lambda i: i >= 0)


def successors(ids: DataFrame) -> DataFrame:
    """ids without ord, and next_uid, in descending (ord, uid), the last followed by the first; windows over ranges of rows of about
    one size, whatever the ids, joined by one row a range."""
    own, keep = F.struct("ord", "uid"), [c for c in ids.columns if c != "ord"]
    dealt = ids.repartitionByRange(common.parts(ids.sparkSession), "ord", "uid").withColumn("range", F.spark_partition_id())
    dealt = common.stage(dealt, "print-ranges")
    heads = dealt.groupBy("range").agg(F.max(own).alias("head"))
    first = heads.agg(F.max("head").alias("first"))
    heads = heads.withColumn("lower", F.lead("head").over(Window.orderBy(F.desc("range"))))  # a row per range
    heads = heads.crossJoin(F.broadcast(first)).select("range", F.coalesce("lower", "first").alias("lower"))  # one row
    after = F.lead(own).over(Window.partitionBy("range").orderBy(F.desc("ord"), F.desc("uid")))
    return dealt.withColumn("after", after).join(F.broadcast(heads), "range").select(*keep, F.coalesce(F.col("after.uid"), F.col("lower.uid")).alias("next_uid"))


def compare_with_edits(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Fingerprints of all texts and of their edited forms, with likenesses to both the edited text and the successor."""
    rows = docs.select(common.col(key).cast("long").alias("doc_id"), common.clean_text(common.col(text)).alias("text"))
    rows = common.identified(rows, "doc_id", ["doc_id", "text"])
    texts = rows.select("uid", "text")
    links = common.stage(successors(rows.select("uid", "ord", "doc_id", F.length("text").cast("long").alias("n_chars"))), "print-links")
    cut = F.floor(F.col("n_chars") / 3).cast("int")
    # both joins read the same exchange of the texts, so both take the same columns of them
    wanted = links.select(F.col("next_uid").alias("uid"), F.col("uid").alias("by"), "doc_id", cut.alias("cut")).hint("merge")
    given = texts.join(wanted, "uid").select(
        F.col("by").alias("uid"), "doc_id", "cut", F.substring("text", F.lit(1), F.col("cut")).alias("patch"), sections(fingerprint(tree(F.col("text")))).alias("next_sections")
    )
    both = texts.join(given.hint("merge"), "uid").withColumn("n_chars", F.length("text").cast("long"))
    both = both.withColumn("edited", F.concat(F.substring("text", F.lit(1), (F.col("n_chars") - F.col("cut")).cast("int")), F.col("patch")))
    both = both.withColumn("fingerprint", fingerprint(tree(F.col("text")))).withColumn("edited_fingerprint", fingerprint(tree(F.col("edited"))))
    both = both.withColumn("sections", sections(F.col("fingerprint"))).withColumn("edited_sections", sections(F.col("edited_fingerprint")))
    return both.select(
        "doc_id",
        "n_chars",
        F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"),
        "fingerprint",
        "edited_fingerprint",
        likeness(F.col("sections"), F.col("edited_sections")).alias("near_edited"),
        likeness(F.col("sections"), F.col("next_sections")).alias("near_next"),
        changed_sections(F.col("sections"), F.col("edited_sections")).alias("changed_sections"),
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compare_with_edits(spark.read.parquet(f"{sf_dir}/documents.parquet"))
