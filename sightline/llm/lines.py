"""Drop lines that many documents share. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACES, UPPER, saved


def lines_of(text: Column) -> Column:
    """The text split at newlines; null or empty: one empty line."""
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def key_of(line: Column) -> Column:
    """The line without white space at both ends, A-Z lower-cased; lines of ASCII take the faster function with the same result."""
    bare = F.btrim(line, F.lit(SPACES))
    return F.when(F.length(bare) == F.octet_length(bare), F.lower(bare)).otherwise(F.translate(bare, UPPER, UPPER.lower()))


def dedup_lines(docs: DataFrame, least_chars: int = 20, least_docs: int = 3) -> DataFrame:
    """Adds n_lines, n_dropped and kept_text to the rows of ``docs`` (doc_id, text).

    A line of at least ``least_chars`` code points (by its key) that at least ``least_docs`` distinct documents
    hold is dropped everywhere but in the largest doc_id that holds it. Keys are hashed once, to 128 bits; the hashes, not the lines, are
    counted, with map-side combine per (hash, document), so a line that a third of all documents hold is no hot task. The way back
    is a join of written tables, which adaptive execution can split, and gives each document the places of its lost lines.
    Rows with equal doc_id count as one document; a null doc_id neither counts nor loses lines. Null and empty texts have one empty
    line, repeated rows stay. Other columns stay, except that columns named like the results are replaced.
    """
    version = F.xxhash64(F.coalesce("text", F.lit("")))
    base = docs.drop("n_lines", "n_dropped", "kept_text", "_places", "_version").withColumn("_version", version)
    long = F.when(F.length("line") >= least_chars, key_of(F.col("line")))
    keyed = saved(
        docs.where("doc_id is not null").select("doc_id", version.alias("_version"), F.posexplode(lines_of(F.col("text"))).alias("place", "line"))
        .select("doc_id", "_version", "place", long.alias("key")).where(F.length("key") >= least_chars)
        .select("doc_id", "_version", "place", F.xxhash64("key").alias("x"), F.xxhash64(F.lit(17), "key").alias("y")),
        "line-hashes",
    )
    common = saved(
        keyed.groupBy("x", "y", "doc_id").agg(F.count(F.lit(1)).alias("seen"))
        .groupBy("x", "y").agg(F.count(F.lit(1)).alias("n"), F.max("doc_id").alias("keeper")).where(F.col("n") >= least_docs).drop("n"),
        "common-lines",
    )
    drops = (
        keyed.join(common, ["x", "y"]).where("doc_id <> keeper")
        .groupBy("doc_id", "_version").agg(F.collect_set("place").alias("_places"))
    )
    kept = F.filter(lines_of(F.col("text")), lambda l, i: ~F.array_contains("_places", i))
    whole = F.col("_places").isNull()
    return base.join(drops, ["doc_id", "_version"], "left").withColumns({
        "n_lines": F.size(lines_of(F.col("text"))).cast("long"),
        "n_dropped": F.when(whole, F.lit(0)).otherwise(F.size("_places")).cast("long"),
        "kept_text": F.when(whole, F.coalesce("text", F.lit(""))).otherwise(F.array_join(kept, "\n")),
    }).drop("_places", "_version")
