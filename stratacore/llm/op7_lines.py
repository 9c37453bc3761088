"""Line deduplication by levelled sorted runs of line hashes. DataFrame functions only.

A line's key is the line without white space at its ends, A-Z lower-cased; its hash is the key's md5 (128 bits).
`LineRuns` keeps runs, each bucketed and sorted by hash, so that runs meet each other and a new batch by merging,
bucket by bucket, and no run is shuffled again. A batch of documents is shuffled once to those buckets, anti-joins what
the runs own, adds the keys it is first to hold as their owner, and counts for the keys that a run owns already.
`FANOUT` runs of a level are compacted into one of the next. After the last batch one compaction gives, per key, the
number of documents and the owner. Fed in descending doc_id order, the owner is the largest doc_id that holds the key.

Edge cases: null or empty text is one empty line; every input row is one document; rows of one doc_id keep or lose a
key's lines together; null doc_ids come last (they are smaller than any id) and are one owner; keys shorter than
min_chars always stay; other columns pass through, whatever their names; empty table: empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..runtime import bucketed
from .common import SPACE_CHARS, ascii_lower, drop_written, packed, written

FANOUT = 3
MIN_CHARS, MIN_DOCS, BATCHES = 20, 3, 4
NO_ID = -(2**63)


def _stripped(line: Column) -> Column:
    return F.btrim(line, F.lit(SPACE_CHARS))


def _hash(line: Column) -> Column:
    return F.md5(ascii_lower(_stripped(line)))


def _lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n", -1)


def _long(line: Column, min_chars: int) -> Column:
    return F.char_length(_stripped(line)) >= min_chars


def line_keys(docs: DataFrame, id_column: str, text_column: str, min_chars: int = MIN_CHARS) -> DataFrame:
    """(doc, keys array<string>): each row's distinct line hashes."""
    keys = F.transform(F.filter(_lines(F.col(text_column)), lambda x: _long(x, min_chars)), _hash)
    return docs.select(F.col(id_column).cast("long").alias("doc"), F.array_distinct(keys).alias("keys")).where(F.size("keys") > 0)


class LineRuns:
    """Sorted runs (key, n_docs, owner); a key's owner is set in the one run whose batch held it first."""

    def __init__(self, spark: SparkSession, fanout: int = FANOUT):
        self.spark, self.fanout, self.levels = spark, fanout, [[]]

    def add(self, batch: DataFrame) -> DataFrame:
        """Take in (doc, keys) rows; returns the batch's run, in which new keys have an owner."""
        found = batch.select("doc", F.explode("keys").alias("key")).groupBy("key").agg(F.count(F.lit(1)).alias("n_docs"), F.max(F.coalesce("doc", F.lit(NO_ID))).alias("owner"))
        for run in (r for level in self.levels for r in level):
            owned = run.where("owner is not null").select("key", F.lit(True).alias("owned"))
            found = found.join(owned.hint("merge"), "key", "left").select("key", "n_docs", F.when(F.col("owned").isNull(), F.col("owner")).alias("owner"))
        run = bucketed(found, "line-run", "key")
        self.levels[0].append(run)
        for k, level in enumerate(self.levels):
            if len(level) >= self.fanout:
                self._merge(level, k + 1)
        return run

    def compacted(self) -> DataFrame:
        """One run of all: (key, n_docs, owner)."""
        rest = [r for level in self.levels for r in level]
        if len(rest) > 1:
            merged = self._compaction(rest)
            drop_written(*rest)
            self.levels = [[], [merged]]
            return merged
        return rest[0] if rest else self.spark.createDataFrame([], "key string, n_docs long, owner long")

    def close(self) -> None:
        """Delete the runs."""
        drop_written(*[r for level in self.levels for r in level])
        self.levels = [[]]

    def _merge(self, level: list[DataFrame], to: int) -> None:
        merged = self._compaction(level)
        drop_written(*level)
        level.clear()
        if to == len(self.levels):
            self.levels.append([])
        self.levels[to].append(merged)

    def _compaction(self, runs: list[DataFrame]) -> DataFrame:
        """Runs joined two by two by merging: counts are added, the one owner of a key stays."""
        out = runs[0]
        for run in runs[1:]:
            more = run.select("key", F.col("n_docs").alias("more_docs"), F.col("owner").alias("more_owner"))
            both = out.join(more.hint("merge"), "key", "full")
            out = both.select("key", (F.coalesce("n_docs", F.lit(0)) + F.coalesce("more_docs", F.lit(0))).alias("n_docs"), F.greatest("owner", "more_owner").alias("owner"))
        return bucketed(out, "line-run", "key")


def dedup_lines(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS, batches: int = BATCHES) -> DataFrame:
    """docs with text_column rewritten and n_lines, n_dropped added (input columns of these names are replaced)."""
    spark = docs.sparkSession
    docs = docs.drop("n_lines", "n_dropped")
    keys = written(line_keys(docs, id_column, text_column, min_chars), "line-keys")
    cuts = keys.agg(F.percentile_approx("doc", [k / batches for k in range(1, batches)], 1000)).first()[0] or []
    runs, top = LineRuns(spark), None
    for cut in [*sorted(set(cuts), reverse=True), None]:
        part = keys if top is None else keys.where(F.col("doc").isNull() | (F.col("doc") < top))
        runs.add(part.where(F.col("doc") >= cut) if cut is not None else part)
        top = cut
    drop = runs.compacted().where(F.col("n_docs") >= min_docs).select("key", "owner")
    pairs = keys.select(F.coalesce("doc", F.lit(NO_ID)).alias("doc"), F.explode("keys").alias("key")).join(drop, "key").where(F.col("doc") != F.col("owner"))
    dropped = written(pairs.groupBy("doc").agg(F.collect_set("key").alias("dropped")), "dropped-lines")
    runs.close()
    drop_written(keys)
    # The input's columns travel as one struct, so that none of their names can clash with those used here.
    names = docs.columns
    whole = docs.select(packed(docs))
    at = {c: F.col("row")[f"c{k}"] for k, c in enumerate(names)}
    # Joined by merging at any size: what is dropped grows with the documents.
    both = whole.withColumn("doc", F.coalesce(at[id_column].cast("long"), F.lit(NO_ID))).join(dropped.hint("merge"), "doc", "left")
    lines = _lines(at[text_column])
    kept = F.filter(lines, lambda x: ~(_long(x, min_chars) & F.array_contains(F.col("dropped"), _hash(x))))
    both = both.select("row", F.size(lines).cast("long").alias("n_lines"), F.when(F.col("dropped").isNull(), lines).otherwise(kept).alias("kept"))
    text = F.array_join("kept", "\n")
    return both.select(*[text.alias(c) if c == text_column else at[c].alias(c) for c in names], "n_lines", (F.col("n_lines") - F.size("kept")).alias("n_dropped"))
