"""Exact dedup against a persistent digest index.

The index is a list of immutable runs (`runs.py`) of digests, each bucketed and
sorted by digest.  A batch is reduced to its distinct digests before anything is
shuffled and meets every run in a sort-merge anti-join that needs no exchange of
the run; what is left is new and appended, with the batch's counts of texts that
are known.  A text that a third of all rows share is one row there; only the join
that gives each document its answer sees it again, where adaptive execution splits
it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .runs import Runs
from .shared import discard, free_name, fresh_path, partitions, quoted, release, stored

#: Batches that a whole table is taken in by, and runs that an index has before they are merged.
BATCHES, FAN_IN = 3, 2


def text_digest(text: Column) -> Column:
    """SHA-256 of the text in UTF-8; null counts as empty.  Texts are equal only if identical."""
    return F.unhex(F.sha2(F.coalesce(text, F.lit("")), 256))


def _merged(rows: DataFrame) -> DataFrame:
    """One row for each digest: the largest id and how many rows have it, the rows in all, and the batch that brought the text."""
    each = rows.groupBy("digest", "keep_id").agg(F.sum("n_keep").alias("n_keep"), F.sum("seen").alias("seen"), F.min("born").alias("born"))
    best = each.groupBy("digest").agg(F.max(F.struct("keep_id", "n_keep")).alias("m"), F.sum("seen").alias("seen"), F.min("born").alias("born"))
    return best.select("digest", "m.keep_id", "m.n_keep", "seen", "born")


class DigestIndex:
    """Digests of all texts seen so far in shared storage, that batches are deduplicated against and appended to."""

    def __init__(self, spark: SparkSession, location: str, buckets: int, id_type: str, fan_in: int = FAN_IN):
        self.location, self.buckets = location, buckets
        self.runs = Runs(spark, location, f"digest BINARY, keep_id {id_type}, n_keep BIGINT, seen BIGINT, born BIGINT", "digest", buckets, fan_in)

    @classmethod
    def create(cls, spark: SparkSession, id_type: str = "BIGINT", location: str | None = None) -> DigestIndex:
        return cls(spark, location or fresh_path(spark, "digest-index"), partitions(spark), id_type)

    def rows(self) -> DataFrame:
        """(digest, keep_id, n_keep, seen, born): one row for each text."""
        runs = self.runs.rows()
        return self.runs.spark.createDataFrame([], self.runs.schema) if runs is None else _merged(runs)

    def ingest(self, digests: DataFrame, batch: int | None = None) -> int:
        """Take in a batch (columns id, digest); its number.

        Texts that no earlier batch has are found by an anti-join with each run and
        appended as born in this batch; of the others the batch's counts are.  A
        batch that failed half-way is taken in again under its number, with the same
        outcome.
        """
        batch = batch or self.runs.next_batch()
        own = digests.groupBy("digest", "id").count().groupBy("digest").agg(F.max(F.struct("id", "count")).alias("m"), F.sum("count").alias("seen"))
        own = stored(own.select("digest", F.col("m.id").alias("keep_id"), F.col("m.count").alias("n_keep"), "seen"), "batch-digests")
        fresh = own
        for run in self.runs.tables(before=batch):
            fresh = fresh.join(run.select("digest").hint("merge"), "digest", "left_anti")
        fresh = stored(fresh.withColumn("born", F.lit(batch).cast("long")), "fresh-digests")
        known = own.join(fresh.select("digest"), "digest", "left_anti").withColumn("born", F.lit(None).cast("long"))
        self.runs.append(fresh.union(known), batch)
        discard(own, fresh)
        self.runs.compact(_merged)
        return batch


def _taken_in(docs: DataFrame, index: DigestIndex, ident: str, text: str, batches: int) -> tuple[DataFrame, DataFrame]:
    """(id, digest) of every row, and (digest, keep_id, n_keep, seen, fresh) of their texts when the index has them all; fresh: was the text unknown before?"""
    digests = stored(docs.select(quoted(ident).alias("id"), text_digest(quoted(text)).alias("digest")), "digests")
    before = index.runs.next_batch()
    for b in range(batches):
        index.ingest(digests if batches == 1 else digests.where(F.pmod(F.xxhash64("id"), F.lit(batches)) == b))
    mine = digests.select("digest").distinct()
    # not read as buckets: a join of two exchanged sides is one that adaptive execution can split
    state = stored(index.rows().join(mine, "digest", "left_semi").withColumn("fresh", F.col("born") >= before).drop("born"), "digest-answers")
    release(docs.sparkSession)
    return digests, state


def deduplicate(docs: DataFrame, index: DigestIndex, ident: str = "doc_id", text: str = "text", batches: int = BATCHES) -> DataFrame:
    """(ident, keep_id, group_size, kept, text_sha256): one row for each row of `docs`, dropped ones too.

    The row with the largest id stays, among the rows of `docs` and all that the
    index took in before.  Null texts are equal to empty ones.  A null id is smaller
    than any other.  Repeated rows with one id and text are all marked kept if that
    id is.  The table is taken in as `batches` by a hash of the id.
    """
    digests, found = _taken_in(docs, index, ident, text, batches)
    kept = F.col("id").eqNullSafe(F.col("keep_id"))
    return digests.join(found, "digest").select(F.col("id").alias(ident), "keep_id", F.col("seen").alias("group_size"), kept.alias("kept"), F.lower(F.hex("digest")).alias("text_sha256"))


def unique_rows(docs: DataFrame, index: DigestIndex, ident: str = "doc_id", text: str = "text", batches: int = BATCHES) -> DataFrame:
    """The rows of `docs` that stay, with all columns: exactly one of each text that the index did not have before.

    Of equal texts the largest id stays; of repeated rows with that id, any one.
    """
    _, found = _taken_in(docs, index, ident, text, batches)
    d, i, wd, wi, n = (free_name(docs, x) for x in ("own_digest", "own_id", "won_digest", "won_id", "won_rows"))
    marked = docs.withColumns({d: text_digest(quoted(text)), i: quoted(ident)})
    winners = found.where("fresh").select(F.col("digest").alias(wd), F.col("keep_id").alias(wi), F.col("n_keep").alias(n))
    same = (F.col(d) == F.col(wd)) & F.col(i).eqNullSafe(F.col(wi))
    kept = marked.join(winners.where(F.col(n) == 1), same, "left_semi").select(*docs.columns)
    ties = winners.where(F.col(n) > 1)
    if ties.isEmpty():
        return kept
    return kept.union(marked.join(ties, same, "left_semi").dropDuplicates([d]).select(*docs.columns))
