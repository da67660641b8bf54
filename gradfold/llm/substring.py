"""Substring dedup with a log-structured index of window fingerprints.

A window is `window` consecutive words.  Instead of all windows the index holds
each window's *anchor*, its smallest run of `gram` words: equal windows have equal
anchors, and neighbouring windows mostly share theirs, so there are about
2 / (window - gram + 2) anchors a word.  The index is a list of immutable runs
(`runs.py`), each sorted and bucketed by anchor hash, one from each batch; when
there are more than `fan_in` of them they are merged into one.  A second list of
runs holds the digests of whole texts, so that copies of a text need no windows.

A batch is deduplicated in two steps.  Its anchors are merge-joined with each run
and with each other, which leaves those that stand in more than one document.
Only for windows with such an anchor is the full fingerprint made - 128 bits of a
cryptographic digest of the words themselves, which is the verification - for
the batch and for the earlier documents that its anchors met.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels
from .runs import Runs
from .shared import append_struct, discard, fresh_path, partitions, quoted, release, stored

WINDOW, GRAM = 50, 25
#: Batches that a whole table is taken in by, and runs that an index has before they are merged.
BATCHES, FAN_IN = 3, 2


def _rows(df: DataFrame, schema: str, text: str, work) -> DataFrame:
    def run(batches):
        for batch in batches:
            for part in kernels.slices(batch, text):
                out = work(part)
                if out is not None and out.num_rows:
                    yield out

    return df.mapInArrow(run, schema)


def _windows(part: pa.RecordBatch, text: str, window: int, gram: int):
    """The words of a slice, and each window's first word, document and anchor."""
    words = kernels.spaced_words(*kernels.text_bytes(part.column(part.schema.get_field_index(text))))
    hashes = words.hashes()
    n = len(hashes)
    doc_of = np.repeat(np.arange(len(words.counts)), words.counts)
    begin = np.arange(max(0, n - window + 1))
    inside = begin + window <= words.first[1:][doc_of[begin]] if len(begin) else begin.astype(bool)
    anchor = kernels.minimizers(hashes, gram, window)[inside]
    begin = begin[inside]
    return words, hashes, begin, doc_of[begin] if n else begin, anchor


def anchors(docs: DataFrame, text: str, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """(h, id, x): the anchors of each document's windows; documents with fewer words have none.  `docs` has id and x."""

    def work(part):
        words, hashes, begin, doc, anchor = _windows(part, text, window, gram)
        at, first = np.unique(anchor, return_index=True)
        if not len(at):
            return None
        h = kernels.mixed(kernels.rolling(hashes, at, at + gram, kernels._STEP)).view(np.int64)
        both = np.unique(np.stack([doc[first], h]), axis=1)  # once in a document is enough
        rows = pa.array(both[0])
        return pa.RecordBatch.from_arrays([pa.array(both[1]), *(part.column(part.schema.get_field_index(c)).take(rows) for c in ("id", "x"))], names=["h", "id", "x"])

    kind = docs.schema["id"].dataType.simpleString()
    return _rows(docs.select("id", "x", quoted(text)), f"h long, id {kind}, x long", text, work)


WINDOWS = T.ArrayType(T.StructType([T.StructField(n, T.LongType(), False) for n in ("h1", "h2", "at")]), False)


def _marked_windows(part: pa.RecordBatch, text: str, marked: str, window: int, gram: int) -> pa.ListArray:
    """For each text the windows whose anchor is in its array `marked`, by 128 bits of the digest of their words."""
    words, hashes, begin, doc, anchor = _windows(part, text, window, gram)
    lists = part.column(part.schema.get_field_index(marked))
    flat = np.asarray(lists.flatten()).astype(np.int64).view(np.uint64)
    owner = np.repeat(np.arange(part.num_rows), np.asarray(lists.value_lengths().fill_null(0)))
    at, back = np.unique(anchor, return_inverse=True)
    h = kernels.mixed(kernels.rolling(hashes, at, at + gram, kernels._STEP))
    mine = lambda h, d: kernels.mixed(h ^ kernels.mixed(d.astype(np.uint64) + np.uint64(1)))  # noqa: E731  marked for this document
    good = np.isin(mine(h[back], doc), mine(flat, owner)) if len(at) and len(flat) else np.zeros(len(begin), bool)
    begin, doc = begin[good], doc[good]
    pair = np.zeros((0, 2), np.int64)
    if len(begin):
        size = words.ends - words.starts
        to = np.cumsum(size + 1)
        spelt = np.full(int(to[-1]), 0x20, np.uint8)  # all words of the slice, each with one space after it
        place = np.arange(int(size.sum())) + np.repeat(np.arange(len(size)), size)
        spelt[place] = words.data[np.repeat(words.starts - (to - size - 1), size) + place]
        raw, digest = spelt.tobytes(), hashlib.blake2b
        start, end = (to - size - 1)[begin], to[begin + window - 1] - 1
        sums = b"".join([digest(raw[a:b], digest_size=16).digest() for a, b in zip(start.tolist(), end.tolist(), strict=True)])
        pair = np.frombuffer(sums, np.int64).reshape(-1, 2)
    cuts = np.searchsorted(doc, np.arange(part.num_rows + 1)).astype(np.int32)
    structs = pa.StructArray.from_arrays([pa.array(pair[:, 0].copy()), pa.array(pair[:, 1].copy()), pa.array((begin - words.first[doc]).astype(np.int64))], ["h1", "h2", "at"])
    return pa.ListArray.from_arrays(pa.array(cuts), structs)


def _digest(words: list[bytes]) -> str:
    return hashlib.sha256(b" ".join(words)).hexdigest()


FIRST = T.StructType([T.StructField("n_words", T.LongType(), False), T.StructField("n_removed", T.LongType(), False), T.StructField("kept", T.StringType(), True), T.StructField("text", T.StringType(), True), T.StructField("windows", WINDOWS, False)])


def _first_pass(docs: DataFrame, window: int, gram: int, digest: bool) -> DataFrame:
    """(id, x, s): the answer for documents that share no anchor and for copies of a whole text, and for others their text and windows."""

    def work():
        def each(part):
            col = lambda c: part.column(part.schema.get_field_index(c))
            data, offs = kernels.text_bytes(col("text"))
            raw, cuts = data.tobytes(), offs.tolist()
            n, gone, kept, texts = [], [], [], []
            for a, b, copy, open_ in zip(cuts, cuts[1:], col("copy").to_pylist(), col("marked").is_valid().to_pylist(), strict=False):
                words = raw[a:b].split()
                n.append(len(words))
                gone.append(len(words) if copy and len(words) >= window else 0)
                left = [] if gone[-1] else words
                undecided = open_ and not copy
                kept.append(None if undecided else _digest(left) if digest else b" ".join(left).decode("utf-8", "replace"))
                texts.append(raw[a:b].decode("utf-8", "replace") if undecided else None)
            return {"n_words": n, "n_removed": gone, "kept": kept, "text": texts, "windows": _marked_windows(part, "text", "marked", window, gram)}

        return each

    return append_struct(docs, "s", FIRST, "text", work, keep=["id", "x"])


class FingerprintIndex:
    """What earlier batches hold: runs of anchors (h, id), and runs of whole texts (d, lo) with the smallest id of each."""

    def __init__(self, spark: SparkSession, location: str | None = None, fan_in: int = FAN_IN, id_type: str = "BIGINT"):
        self.location = location or fresh_path(spark, "window-index")
        self.anchors = Runs(spark, f"{self.location}/anchors", f"h BIGINT, id {id_type}", "h", partitions(spark), fan_in)
        self.texts = Runs(spark, f"{self.location}/texts", f"d BINARY, lo {id_type}", "d", partitions(spark), fan_in)

    def next_batch(self) -> int:
        return self.texts.next_batch()  # texts are appended last

    def append(self, anchors: DataFrame, texts: DataFrame, batch: int) -> None:
        self.anchors.append(anchors, batch)
        self.texts.append(texts, batch)

    def compact(self) -> None:
        self.anchors.compact(lambda rows: rows.distinct())
        self.texts.compact(lambda rows: rows.groupBy("d").agg(F.min("lo").alias("lo")))


def _met(here: DataFrame, runs: list[DataFrame], key: str) -> DataFrame | None:
    """The rows of earlier runs whose key the batch has: a merge join with each run, that exchanges nothing of it."""
    out = None
    for run in runs:
        one = run.join(here.select(key).hint("merge"), key, "left_semi")
        out = one if out is None else out.union(one)
    return out


KEPT = T.StructType([T.StructField("n_words", T.LongType(), False), T.StructField("n_removed", T.LongType(), False), T.StructField("kept", T.StringType(), False)])


def _without(docs: DataFrame, text: str, starts: str, keep: list[str], window: int, into: str, digest: bool) -> DataFrame:
    """Take out the words under the windows that begin at the words in array `starts`; `digest`: give the SHA-256 of what stays."""

    def work():
        def each(part):
            texts = kernels.text_bytes(part.column(part.schema.get_field_index(text)))
            raw, cuts = texts[0].tobytes(), texts[1].tolist()
            lists = part.column(part.schema.get_field_index(starts)).to_pylist()
            n, gone, kept = [], [], []
            for a, b, at in zip(cuts, cuts[1:], lists, strict=False):
                words = raw[a:b].split()
                n.append(len(words))
                if at:
                    cover = np.zeros(len(words) + 1, np.int64)
                    np.add.at(cover, at, 1)
                    np.add.at(cover, np.array(at) + window, -1)
                    stay = np.cumsum(cover[:-1]) == 0
                    words = [w for w, s in zip(words, stay.tolist(), strict=True) if s]
                gone.append(n[-1] - len(words))
                left = b" ".join(words)
                kept.append(hashlib.sha256(left).hexdigest() if digest else left.decode("utf-8", "replace"))
            return {"n_words": n, "n_removed": gone, "kept": kept}

        return each

    return append_struct(docs, into, KEPT, text, work, keep)


def deduplicate_batch(batch: DataFrame, index: FingerprintIndex, earlier: DataFrame | None = None, ident: str = "doc_id", text: str = "text", window: int = WINDOW, gram: int = GRAM, digest: bool = False, number: int | None = None) -> DataFrame:
    """(ident, n_words, n_removed, kept): what is left of each document of a batch, which is then part of the index.

    A word goes if a window over it has words that also begin a window in a
    document with a smaller id, in the batch or in `earlier`, the documents that
    the index has taken in (their ids must be smaller than the batch's).  Windows
    are judged on the texts as they came.  `kept` joins the words that stay by one
    space; with `digest` it is the SHA-256 of that instead.  Null texts have no
    words.  Rows with a null id are left whole and not indexed.  Rows that share
    an id are parts of one document and never judged against each other.

    The text is exchanged once, and that of documents with a shared anchor once
    more.  Whole texts that repeat go by their digests and send no windows.  A batch
    that failed half-way is taken in again under its number.
    """
    spark, kind = batch.sparkSession, batch.schema[ident].dataType.simpleString()
    number = number or index.next_batch()
    key = [quoted(ident).alias("id"), quoted(text).alias("text"), F.xxhash64(quoted(text)).alias("x")]
    docs = batch.select(*key)
    # copies of a whole text with a smaller id: all their windows are that one's
    whole = stored(docs.where("id is not null and text is not null").select("id", "x", F.unhex(F.sha2("text", 256)).alias("d")), "text-digests")
    firsts = stored(whole.groupBy("d").agg(F.min("id").alias("lo"), F.max("id").alias("hi")), "first-texts")
    known = _met(firsts, index.texts.tables(before=number), "d")
    repeated = firsts.where("lo != hi").select("d", "lo")
    if known is not None:
        known = stored(known, "known-texts")
        repeated = repeated.union(known).groupBy("d").agg(F.min("lo").alias("lo"))
    repeated = stored(repeated, "repeated-texts")
    copies = stored(whole.join(repeated, "d").where("id > lo").select("id", "x").distinct(), "copies")
    own = stored(anchors(docs.where("id is not null"), "text", window, gram).join(copies, ["id", "x"], "left_anti"), "anchors")
    here = stored(own.groupBy("h").agg(F.min("id").alias("lo"), F.max("id").alias("hi")), "own-anchors")
    old = _met(here, index.anchors.tables(before=number), "h")
    met = here.where("lo != hi").select("h")
    if old is not None:
        old = stored(old, "met-history")
        met = met.union(old.select("h")).distinct()
    met = stored(met, "met")
    index.append(own.select("h", "id").distinct(), firsts.select("d", "lo"), number)
    release(spark)
    marks = own.join(met, "h").groupBy("id", "x").agg(F.collect_set("h").alias("marked"))  # a document's own anchors
    info = marks.withColumn("copy", F.lit(False)).union(copies.select("id", "x", F.lit(None).cast("array<bigint>"), F.lit(True)))
    first = stored(_first_pass(docs.join(info, ["id", "x"], "left").withColumn("copy", F.coalesce("copy", F.lit(False))), window, gram, digest), "first-pass")
    release(spark)
    open_ = first.where("s.text is not null")
    windows = open_.select("id", "x", F.explode("s.windows").alias("w")).select("id", "x", "w.*")
    every, spare = windows.select("h1", "h2", "id"), []
    if old is not None and earlier is not None:
        # of the earlier documents only those that hold an anchor of the batch are read again
        held = old.groupBy(F.col("id").alias("old_id")).agg(F.collect_set("h").alias("marked"))
        before = earlier.select(*key).join(held, F.col("id") == F.col("old_id")).drop("old_id").withColumn("copy", F.lit(False))
        again = _first_pass(before, window, gram, digest).select("id", F.explode("s.windows").alias("w"))
        again = stored(again.groupBy("w.h1", "w.h2").agg(F.min("id").alias("id")), "earlier-windows")
        every, spare = every.union(again), [again]
        release(spark)
    least = every.groupBy("h1", "h2").agg(F.min("id").alias("lo"), F.max("id").alias("hi")).where("lo != hi").select("h1", "h2", "lo")
    least = stored(least, "shared-windows")
    release(spark)
    late = windows.join(least, ["h1", "h2"]).where("id > lo").groupBy("id", "x").agg(F.collect_set("at").alias("starts"))
    made = _without(open_.select("id", "x", "s.text").join(late, ["id", "x"], "left"), "text", "starts", ["id"], window, "s", digest)
    done = first.where("s.text is null")
    out = done.select("id", "s.n_words", "s.n_removed", "s.kept").union(made.select("id", "s.n_words", "s.n_removed", "s.kept"))
    out = stored(out.select(F.col("id").cast(kind).alias(ident), "n_words", "n_removed", "kept"), "batch-answers")
    release(spark)
    discard(whole, firsts, repeated, copies, own, here, met, first, least, *spare, *(x for x in (known, old) if x is not None))
    index.compact()
    release(spark)
    return out


def deduplicate(docs: DataFrame, ident: str = "doc_id", text: str = "text", batches: int = BATCHES, digest: bool = False, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """The same for a whole table by way of a fresh index, taken in as up to `batches` batches of rising ids.

    Ids that can not be put into ranges (other than numbers and dates) make one batch.
    """
    kind = docs.schema[ident].dataType
    index = FingerprintIndex(docs.sparkSession, id_type=kind.simpleString())
    key = quoted(ident)
    probs = [i / batches for i in range(1, batches)] if isinstance(kind, (T.NumericType, T.DatetimeType)) else []
    cuts = sorted(set(docs.agg(F.percentile_approx(key, probs, 1000)).first()[0] or [])) if probs else []
    out, low = None, None
    for high in [*cuts, None]:
        keep = F.lit(True) if low is None else key > low
        if high is not None:
            keep &= key <= high
        else:
            keep |= key.isNull()
        earlier = None if low is None else docs.where(key <= low)
        one = deduplicate_batch(docs.where(keep), index, earlier, ident, text, window, gram, digest)
        out, low = one if out is None else out.union(one), high
    return out
