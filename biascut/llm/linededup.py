"""Line deduplication with levelled sorted runs of line hashes (DataFrame operations only).

Documents arrive in batches of rising doc_id.  The lines seen so far are kept as *runs*: tables of
(key hash, first doc_id), cut by hash into as many buckets as a shuffle has partitions, one sorted
file a bucket.  A batch brings its distinct keys into the same buckets and order by its one exchange;
from there on every run is merge-joined as it lies, without an exchange or a sort: keys that no run
knows become a run of level 0, the others are lines seen before.  When a level holds ``fanout`` runs
they are merge-joined into one run of the next level, so a key is rewritten only logarithmically often.

A key is the line stripped of ASCII white space with A-Z lower-cased; only keys of at least
``min_chars`` code points count.  Two chained 64-bit hashes stand for a key (a corpus of 10^12
lines expects no false match among 128 bits).

Skew.  Runs and batches meet by distinct keys only (partial aggregates).  A line found in a third of
all documents is a hot key in the last join alone, of lines with the keys found twice; both sides are
tables with plain exchanges there, which adaptive execution splits.

Defined cases: null or empty text is one empty line; rows without doc_id neither mark nor lose
lines; rows repeating a doc_id are one document with several texts; an empty table gives an empty result.
"""

from __future__ import annotations

import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import discard, drop, materialize, row_id, scratch_path, shuffle_partitions

BLANKS = " \t\n\x0b\x0c\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
MIN_CHARS = 10
KEY = ["k1", "k2"]
#: Makes a scan of sorted buckets tell its order to the planner; set only while runs are written.
_ORDERED = "spark.sql.legacy.bucketedTableScan.outputOrdering"


def line_keys(text):
    """array<struct<n,k1,k2>> with one entry a line: code points of the key, and its hashes."""
    lowered = F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)
    stripped = F.transform(F.split(lowered, "\n", -1), lambda x: F.btrim(x, F.lit(BLANKS)))
    return F.transform(stripped, lambda x: F.struct(F.char_length(x).alias("n"), F.xxhash64(x).alias("k1"), F.xxhash64(F.lit(7), x).alias("k2")))


@contextmanager
def _ordered_scans(spark: SparkSession):
    before = spark.conf.get(_ORDERED, "false")
    spark.conf.set(_ORDERED, "true")
    try:
        yield
    finally:
        spark.conf.set(_ORDERED, before)


class LineRuns:
    """The levelled store of known line keys, under one folder of the shared scratch space."""

    def __init__(self, spark: SparkSession, fanout: int = 3):
        self.spark, self.fanout, self.levels, self.buckets = spark, fanout, [[]], shuffle_partitions(spark)

    def _write(self, keys: DataFrame, level: int) -> str:
        """``keys`` lie in the buckets already, so every task writes one sorted file."""
        name, path = f"biascut_lines_{uuid.uuid4().hex[:12]}", scratch_path(self.spark, f"lines-l{level}")
        keys.write.format("parquet").option("path", path).bucketBy(self.buckets, *KEY).sortBy(*KEY).saveAsTable(name)
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append((name, path))
        return name

    def _run(self, name: str, k: int) -> DataFrame:
        """The new keys of a run, its first_id renamed."""
        return self.spark.table(name).where("fresh").select(*KEY, F.col("first_id").alias(f"_r{k}"))

    def joined(self, keys: DataFrame) -> DataFrame:
        """A batch's distinct (k1, k2, doc_id, n) with the smallest doc_id of each and whether it is new."""
        known = [F.lit(None).cast("long")]
        for k, (name, _) in enumerate(x for level in self.levels for x in level):
            keys = keys.join(self._run(name, k).hint("merge"), KEY, "left")
            known.append(F.col(f"_r{k}"))
        first = F.coalesce(*known)
        return keys.select(*KEY, F.coalesce(first, "doc_id").alias("first_id"), first.isNull().alias("fresh"), "n")

    def merged(self, names: list[str]) -> DataFrame:
        """Runs as one: they share no key, so a full merge join puts their rows in order."""
        out = self._run(names[0], 0).withColumnRenamed("_r0", "first_id")
        for name in names[1:]:
            out = out.join(self._run(name, 1).hint("merge"), KEY, "full").select(*KEY, F.coalesce("first_id", "_r1").alias("first_id"))
        return out.select(*KEY, "first_id", F.lit(True).alias("fresh"), F.lit(1).cast("long").alias("n"))

    def add(self, batch: DataFrame) -> DataFrame:
        """Merge-joins a batch's (k1, k2, doc_id) against the runs, keeps its new keys as a run, and
        returns (k1, k2, first_id) of the keys that more than one document holds by now."""
        with _ordered_scans(self.spark):
            keys = batch.groupBy(*KEY).agg(F.min("doc_id").alias("doc_id"), F.max("doc_id").alias("_last"))
            keys = keys.select(*KEY, "doc_id", F.when(F.col("_last") > F.col("doc_id"), 2).otherwise(1).cast("long").alias("n"))
            name = self._write(self.joined(keys), 0)
            twice = materialize(self.spark.table(name).where("not fresh or n > 1").select(*KEY, "first_id"), "lines-twice")
            level = 0
            while len(self.levels[level]) >= self.fanout:
                old, self.levels[level] = self.levels[level], []
                self._write(self.merged([n for n, _ in old]), level + 1)
                self._forget(old)
                level += 1
        return twice

    def _forget(self, runs: list[tuple[str, str]]) -> None:
        for name, path in runs:
            self.spark.sql(f"DROP TABLE {name}")
            discard(self.spark, path)

    def close(self) -> None:
        for level in self.levels:
            self._forget(level)
        self.levels = [[]]


def dedup_lines(docs: DataFrame, batches: int = 4, min_chars: int = MIN_CHARS, fanout: int = 3, keep: list[str] | None = None) -> DataFrame:
    """Per document: ``keep`` columns (doc_id by default), n_lines, n_dropped, kept_text."""
    spark = docs.sparkSession
    keep = keep or ["doc_id"]
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.col("doc_id").cast("long").alias("_id"), text.alias("_text"), F.struct(*(F.col(c) for c in keep)).alias("_keep"))
    rows = rows.select(*row_id("_id", "_text"), "_id", "_text", "_keep")
    lines = rows.where("_id is not null").select("_u1", "_u2", F.col("_id").alias("doc_id"), F.posexplode(line_keys(F.col("_text"))).alias("pos", "k"))
    lines = materialize(lines.where(F.col("k.n") >= min_chars).select("_u1", "_u2", "doc_id", "pos", "k.k1", "k.k2"), "line-keys")
    lo, hi = lines.agg(F.min("doc_id"), F.max("doc_id")).first()
    runs, twice = LineRuns(spark, fanout), []
    if lo is not None:
        width = (hi - lo) // batches + 1
        for b in range(batches):
            twice.append(runs.add(lines.where((F.col("doc_id") >= lo + b * width) & (F.col("doc_id") < lo + (b + 1) * width)).select(*KEY, "doc_id")))
        runs.close()
    if twice:
        found = twice[0]
        for t in twice[1:]:
            found = found.unionByName(t)
        found = materialize(found.groupBy(*KEY).agg(F.min("first_id").alias("first_id")), "lines-found-twice")
        drop(*twice)
        gone = lines.join(found, KEY).where("first_id < doc_id")
        # places in one text: the list is bounded by its lines
        gone = gone.groupBy("_u1", "_u2").agg(F.array_sort(F.collect_set("pos")).alias("_gone"))
        rows = rows.join(gone, ["_u1", "_u2"], "left")
    else:
        rows = rows.withColumn("_gone", F.lit(None).cast("array<int>"))
    rows = rows.select("_keep", F.split("_text", "\n", -1).alias("_lines"), F.coalesce("_gone", F.array().cast("array<int>")).alias("_gone"))
    # what lies between two dropped places, in one walk over the lines
    n, last = F.size("_lines"), F.size("_gone")
    begin = lambda k: F.when(k == 0, 0).otherwise(F.element_at("_gone", F.greatest(k, F.lit(1))) + 1)
    end = lambda k: F.when(k == last, n).otherwise(F.element_at("_gone", F.least(k + 1, F.greatest(last, F.lit(1)))))
    parts = F.transform(F.sequence(F.lit(0), last), lambda k: F.slice("_lines", begin(k) + 1, end(k) - begin(k)))
    kept = F.when(last == 0, F.col("_lines")).otherwise(F.flatten(parts))
    return rows.select("_keep.*", n.cast("long").alias("n_lines"), last.cast("long").alias("n_dropped"), F.array_join(kept, "\n").alias("kept_text"))
