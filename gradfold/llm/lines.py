"""Fuzzy line dedup by MinHash.

Lines are sets of character shingles.  Each distinct line gets a signature of
minima under `BANDS * ROWS` hash functions; lines that agree in all rows of a band
are candidates.  One bit of each minimum makes a sketch of the line.  Band keys are
dealt out in packed blocks, and a bucket is ordered where it is read: a line is compared, by sketches, with the bucket's
leaders, and becomes one if it is like none of them, so that a group of near copies
is never expanded into pairs.  Candidates are confirmed by exact Jaccard similarity.
A line that none of its leaders turned out to be similar to is then compared with
the rest of its bucket, but for lines that bit maps of the shingle sets rule out.  Linked lines are joined by distributed union-find, and of
each component the first line stays.

At a similarity of 0.8 a pair is a candidate with probability 0.991, and sketches
keep it apart with probability under 1e-3.
"""

from __future__ import annotations

import hashlib
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels
from .components import components
from .shared import append_struct, discard, partitions, quoted, release, stored

SHINGLE, BANDS, ROWS, SIMILAR = 5, 12, 5, 0.8
#: Differing bits of two sketches above which two lines are not compared (similar ones differ in 6 of 60, with a deviation of 2.3).
APART = 13
#: Signatures work on less text at a time, so that the arrays stay in cache.
PART_BYTES = 1 << 18
#: Distinct lines that a task remembers, to send each only once.
REMEMBERED = 1 << 20
#: Bytes of band keys that a task gathers before it deals them out, and parts of them for each shuffle partition.
GATHERED, PARTS = 24 << 20, 4
#: Bits of the table that tells which lines are wanted, 32 for each of them and so many at most: it is sent to all tasks.
TABLE_BITS = 26
#: Lines near a leader and similar to none from which on the middle of its lines is looked for: fewer have no more than so many pairs for each other line.
HUB = 64
#: 64-bit words of a line's bit map.
MAPS = 8
CELLS = [f"b{i}" for i in range(MAPS)]

_FACTORS = (kernels.mixed(np.arange(1, BANDS * ROWS + 1, dtype=np.uint64)) | np.uint64(1)).astype(np.uint32)


def line_id(line: str) -> bytes:
    return hashlib.blake2b(line.encode(), digest_size=16).digest()


def _hashes(lines: list[str], shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the character shingles of non-empty lines, end to end, and where each line's begin; a line shorter than a shingle is one."""
    ends = np.cumsum(np.fromiter(map(len, lines), np.int64, len(lines)))
    starts = np.concatenate([[0], ends[:-1]])
    chars = np.frombuffer("".join(lines).encode("utf-32-le"), np.uint32).astype(np.uint64)
    short = ends - starts < shingle
    many = np.where(short, 1, ends - starts - shingle + 1)
    first = np.cumsum(many) - many
    # what kernels.rolling gives, by neighbours
    n = max(0, len(chars) - shingle + 1)
    h = chars[shingle - 1 :].copy()
    for i in range(shingle - 2, -1, -1):
        h *= np.uint64(kernels._BASE)
        h += chars[i : i + n]
    whole = np.ones(len(chars), bool)
    for i in range(1, shingle):
        whole[np.maximum(ends - i, 0)] = False
    h = h[whole[:n]]
    if short.any():
        every = np.empty(int(many.sum()), np.uint64)
        of = np.repeat(short, many)
        every[~of] = h
        every[of] = kernels.rolling(chars, starts[short], ends[short], kernels._BASE)
        h = every
    return kernels.mixed(h), first


def _distinct(values: np.ndarray, starts: list[int], ends: list[int]) -> np.ndarray:
    """Sort values[start:end] in place for every pair; which of all values are the first of their kind there."""
    for a, b in zip(starts, ends, strict=True):
        values[a:b].sort()
    fresh = np.ones(len(values), bool)
    np.not_equal(values[1:], values[:-1], out=fresh[1:])
    fresh[starts] = True
    return fresh


def bit_maps(lines: list[str], shingle: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(sizes of the shingle sets, maps of MAPS words) of non-empty lines; a bit of a map is the parity of the shingles in its cell.

    The maps of two sets differ in no more cells than the sets in shingles.
    """
    h, first = _hashes(lines, shingle)
    fresh = _distinct(h, first.tolist(), [*first[1:].tolist(), len(h)])
    line = np.repeat(np.arange(len(lines)), np.diff(np.append(first, len(h))))[fresh]
    h, cells = h[fresh], np.zeros(len(lines) * MAPS, np.uint64)
    np.bitwise_xor.at(cells, line * MAPS + (h >> np.uint64(61)).astype(np.int64), np.uint64(1) << (h >> np.uint64(55) & np.uint64(63)))
    return np.bincount(line, minlength=len(lines)).astype(np.int32), cells.view(np.int64).reshape(-1, MAPS)


def bands(lines: list[str], shingle: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(lines, BANDS) band keys of non-empty lines, and their sketches."""
    h, first = _hashes(lines, shingle)
    h = (h >> np.uint64(32)).astype(np.uint32)
    rows, moved = np.empty((len(_FACTORS), len(lines)), np.uint32), np.empty_like(h)
    for i, f in enumerate(_FACTORS):
        np.multiply(h, f, out=moved)
        np.minimum.reduceat(moved, first, out=rows[i])
    rows = rows.astype(np.uint64)
    out = np.empty((len(lines), BANDS), np.uint64)
    for b in range(BANDS):
        key = np.full(len(lines), b + 1, np.uint64)
        for r in range(ROWS):
            key = kernels.mixed(key + rows[b * ROWS + r])
        out[:, b] = key
    sketch = np.zeros(len(lines), np.uint64)
    for i in range(min(64, len(rows))):
        sketch |= (rows[i] & np.uint64(1)) << np.uint64(i)
    return out.view(np.int64), sketch.view(np.int64)


def jaccard(a: str, b: str, shingle: int = SHINGLE) -> float:
    """Exact similarity of the shingle sets; a line shorter than a shingle is one shingle."""
    s, t = ({x[i : i + shingle] for i in range(max(1, len(x) - shingle + 1))} for x in (a, b))
    return len(s & t) / len(s | t)


def _packed(lines: list[str], shingle: int) -> list[np.ndarray | None]:
    """The shingle set of each line as sorted numbers that hold the characters themselves; None where they don't fit 64 bits or the line is short."""
    bits = min(64 // shingle, 31)
    ends = np.cumsum(np.fromiter(map(len, lines), np.int64, len(lines)))
    starts = np.concatenate([[0], ends[:-1]])
    chars = np.frombuffer("".join(lines).encode("utf-32-le"), np.uint32)
    wide = np.zeros(len(lines), bool)
    wide[np.searchsorted(ends, np.flatnonzero(chars >> np.uint32(bits)), "right")] = True
    good = np.flatnonzero(~wide & (ends - starts >= shingle))
    out: list[np.ndarray | None] = [None] * len(lines)
    if not len(good):
        return out
    n = len(chars) - shingle + 1
    k = chars[:n].astype(np.uint64)
    for i in range(1, shingle):
        k <<= np.uint64(bits)
        k |= chars[i : i + n]
    a, b = starts[good].tolist(), (ends[good] - shingle + 1).tolist()
    fresh = _distinct(k, a, b)
    for i, x, y in zip(good.tolist(), a, b, strict=True):
        out[i] = k[x:y][fresh[x:y]]
    return out


def similarities(left: list[str], right: list[str], shingle: int = SHINGLE) -> list[float]:
    """Exact similarity of pairs of lines, as `jaccard` has it."""
    known = {x: i for i, x in enumerate(dict.fromkeys([*left, *right]))}
    sets, out = _packed(list(known), shingle), []
    for x, y in zip(left, right, strict=True):
        s, t = sets[known[x]], sets[known[y]]
        if s is None or t is None:
            out.append(jaccard(x, y, shingle))
            continue
        both = np.concatenate((s, t))
        both.sort()
        both = int(np.count_nonzero(both[1:] == both[:-1]))
        out.append(both / (len(s) + len(t) - both))
    return out


def _split(text: str | None) -> list[tuple[int, str]]:
    """(place, line) of each line that is not blank."""
    return [(n, x) for n, x in enumerate((text or "").split("\n")) if x and not x.isspace()]


def _occurrences(docs: DataFrame) -> DataFrame:
    """(id, t, at, l1, l2): every line that is not blank; the halves of a digest of 128 bits stand for the line."""

    def work(batches):
        for batch in batches:
            for part in kernels.slices(batch, "text"):
                row, at, ids, known = [], [], [], {}
                for r, t in enumerate(part.column(part.schema.get_field_index("text")).to_pylist()):
                    for n, x in _split(t):
                        found = known.get(x)
                        if found is None:
                            found = known[x] = line_id(x)
                        row.append(r)
                        at.append(n)
                        ids.append(found)
                index, halves = pa.array(row, pa.int64()), np.frombuffer(b"".join(ids), np.int64).reshape(-1, 2)
                cols = [part.column(part.schema.get_field_index(c)).take(index) for c in ("id", "t")]
                yield pa.RecordBatch.from_arrays([*cols, pa.array(at, pa.int32()), pa.array(halves[:, 0].copy()), pa.array(halves[:, 1].copy())], names=["id", "t", "at", "l1", "l2"])

    kind = docs.schema["id"].dataType.simpleString()
    return docs.mapInArrow(work, f"id {kind}, t long, at int, l1 long, l2 long")


PACKED = "part int, rows binary"


def _dealt(pieces, parts: int):
    """(part, rows): the rows (key, lid, sketch) of some arrays of three columns, packed end to end for each part of the keys."""

    def packed(held):
        rows = np.concatenate(held)
        part = ((rows[:, 0].view(np.uint64) >> np.uint64(32)) % np.uint64(parts)).astype(np.uint16 if parts <= 1 << 16 else np.int32)  # of two bytes numpy sorts without comparing
        counts = np.bincount(part, minlength=parts)
        some = np.flatnonzero(counts)
        offsets = np.concatenate([[0], np.cumsum(counts[some])]) * rows.itemsize * 3
        data = rows[np.argsort(part, kind="stable")]
        blobs = pa.Array.from_buffers(pa.binary(), len(some), [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(data)])
        return pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), blobs], names=["part", "rows"])

    held, size = [], 0
    for rows in pieces:
        held.append(rows)
        size += rows.nbytes
        if size >= GATHERED:
            yield packed(held)
            held, size = [], 0
    if size:
        yield packed(held)


def _buckets(batches):
    """(key, lid, sketch) arrays of each part, ordered by key and lid, without the keys of one row."""

    def ordered(blobs):
        rows = np.frombuffer(b"".join(blobs), np.int64).reshape(-1, 3)
        key = rows[:, 0].copy()
        order = np.argsort(key)
        key = key[order]
        same = np.zeros(len(key) + 1, bool)
        np.equal(key[1:], key[:-1], out=same[1:-1])
        rows = rows[order[same[1:] | same[:-1]]]
        rows = rows[np.lexsort((rows[:, 1], rows[:, 0]))]
        return [np.ascontiguousarray(rows[:, i]) for i in range(3)]

    last, blobs = None, []
    for batch in batches:
        for part, rows in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            if blobs and part != last:
                yield ordered(blobs)
                blobs = []
            last = part
            blobs.append(rows.as_buffer())
    if blobs:
        yield ordered(blobs)


def _band_keys(docs: DataFrame) -> DataFrame:
    """(part, rows): the band keys of each line, once a task, as packed rows (key, lid, sketch); lid is the first half of the line's digest."""
    parts = PARTS * partitions(docs.sparkSession)

    def pieces(batches):
        known: set[bytes] = set()
        for batch in batches:
            for part in kernels.slices(batch, "text", PART_BYTES):
                fresh = {}
                for t in part.column(part.schema.get_field_index("text")).to_pylist():
                    for _, x in _split(t):
                        if x not in fresh and (i := line_id(x)) not in known:
                            fresh[x] = i
                if not fresh:
                    continue
                if len(known) > REMEMBERED:
                    known.clear()
                known.update(fresh.values())
                keys, sketch = bands(list(fresh))
                lid = np.frombuffer(b"".join(i[:8] for i in fresh.values()), np.int64)
                yield np.stack([keys.ravel(), np.repeat(lid, BANDS), np.repeat(sketch, BANDS)], axis=1)

    return docs.select("text").mapInArrow(lambda batches: _dealt(pieces(batches), parts), PACKED)


def _near_leaders(group: np.ndarray, lid: np.ndarray, sketch: np.ndarray, free: np.ndarray, apart: int):
    """Rounds over the buckets of a batch: the first free row of each leads and all rows of its bucket are compared with it.

    Gives (near rows, their leaders) for each round and the leaders; rows near a leader are no longer free.
    """
    live, near, leaders = np.arange(len(group)), [], []
    while len(open_ := live[free[live]]):
        starts = np.ones(len(open_), bool)
        starts[1:] = group[open_[1:]] != group[open_[:-1]]
        lead = open_[starts]
        leaders.append(lead)
        of = np.full(int(group[-1]) + 1, -1)
        of[group[lead]] = lead
        live = live[of[group[live]] >= 0]
        head = of[group[live]]
        like = (np.bitwise_count(sketch[live] ^ sketch[head]) <= apart) & (live != head)
        free[lead] = False
        free[live[like]] = False
        near.append((live[like], head[like]))
    return near, leaders


def candidates(keys: DataFrame, apart: int = APART) -> DataFrame:
    """(key, lid, sketch, leader, mark) from rows (key, lid, sketch), packed or not: in each bucket the lines with each of the leaders whose sketch, `mark`, is near their own.

    Leaders are the lines that are near no earlier leader of the bucket.  Work is in
    the lines times the leaders of a bucket; memory is one part of the keys, in
    which a line of a bucket takes 24 bytes.
    """
    if "rows" not in keys.columns:
        parts = PARTS * partitions(keys.sparkSession)
        keys = keys.select("key", "lid", "sketch").mapInArrow(lambda batches: _dealt((np.stack([np.asarray(b.column(i)) for i in range(3)], axis=1) for b in batches if b.num_rows), parts), PACKED)

    def work(batches):
        for key, lid, sketch in _buckets(batches):
            fresh = np.ones(len(key), bool)
            fresh[1:] = (key[1:] != key[:-1]) | (lid[1:] != lid[:-1])
            key, lid, sketch = key[fresh], lid[fresh], sketch[fresh]
            if not len(key):
                continue
            changes = np.ones(len(key), bool)
            changes[1:] = key[1:] != key[:-1]
            near, _ = _near_leaders(np.cumsum(changes) - 1, lid, sketch, np.ones(len(key), bool), apart)
            out = [(key[r], lid[r], sketch[r], lid[h], sketch[h]) for r, h in near]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([o[i] for o in out])) for i in range(5)], names=["key", "lid", "sketch", "leader", "mark"])

    return keys.repartition("part").sortWithinPartitions("part").mapInArrow(work, "key long, lid long, sketch long, leader long, mark long")


def _table(wanted: DataFrame, most: int) -> tuple[int, np.ndarray]:
    """(shift, table) of bits: that of lid >> shift is set for each `lid` of `wanted`, of which there are `most` at most."""
    size = min(TABLE_BITS, max(12, (32 * most).bit_length()))
    cell = F.shiftrightunsigned("lid", 64 - size)
    words = cell.bitwiseAND(F.lit(63)).alias("bit"), F.shiftright(cell, 6).alias("word")
    got = wanted.select(*words).groupBy("word").agg(F.bit_or(F.expr("shiftleft(1L, int(bit))")).alias("bits")).toArrow()  # 2 ** (TABLE_BITS - 6) rows at most
    out = np.zeros(1 << size - 6, np.uint64)
    out[got.column("word").to_numpy()] = got.column("bits").to_numpy().view(np.uint64)
    return 64 - size, out


def _texts(docs: DataFrame, wanted: DataFrame, most: int) -> DataFrame:
    """(l1, l2, x, n, bit map): the text of each line whose l1 is a lid of `wanted`, and of few others, with the size of its shingle set.

    The documents are read once more and only these lines leave their task.
    """
    shared = docs.sparkSession.sparkContext.broadcast(_table(wanted, most))

    def work(batches):
        shift, bits = shared.value
        known: set[bytes] = set()
        for batch in batches:
            for part in kernels.slices(batch, "text", PART_BYTES):
                lines = list({x: None for t in part.column(part.schema.get_field_index("text")).to_pylist() for _, x in _split(t)})
                ids = [line_id(x) for x in lines]
                halves = np.frombuffer(b"".join(ids), np.int64).reshape(-1, 2)
                cell = halves[:, 0].view(np.uint64) >> np.uint64(shift)
                at = np.flatnonzero(bits[(cell >> np.uint64(6)).astype(np.int64)] >> (cell & np.uint64(63)) & np.uint64(1))
                at = np.array([i for i in at.tolist() if ids[i] not in known], np.int64)
                if not len(at):
                    continue
                if len(known) > REMEMBERED:
                    known.clear()
                known.update(ids[i] for i in at.tolist())
                lines = [lines[i] for i in at.tolist()]
                n, maps = bit_maps(lines)
                cols = [pa.array(halves[at, 0]), pa.array(halves[at, 1]), pa.array(lines, pa.string()), pa.array(n)]
                yield pa.RecordBatch.from_arrays([*cols, *(pa.array(np.ascontiguousarray(maps[:, i])) for i in range(MAPS))], names=["l1", "l2", "x", "n", *CELLS])

    found = docs.select("text").mapInArrow(work, "l1 long, l2 long, x string, n int, " + ", ".join(f"{c} long" for c in CELLS))
    return found.dropDuplicates(["l1", "l2"])


def _compared(pairs: DataFrame, texts: DataFrame, shingle: int) -> DataFrame:
    """(a, b, na, nb, like) for pairs (a, b) of lids: the lines as (l1, l2) and their similarity."""

    def work(batches):
        for batch in batches:
            left, right, like = batch.column(4).to_pylist(), batch.column(5).to_pylist(), []
            size = np.cumsum([len(x) + len(y) for x, y in zip(left, right, strict=True)])
            cuts = [0, *(np.flatnonzero(np.diff(size // PART_BYTES)) + 1).tolist(), len(left)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                like += similarities(left[a:b], right[a:b], shingle)
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(4)), pa.array(like, pa.float64())], names=["a", "b", "na", "nb", "like"])

    node = F.struct("l1", "l2")
    left = texts.select(F.col("l1").alias("a"), node.alias("na"), F.col("x").alias("xa"))
    right = texts.select(F.col("l1").alias("b"), node.alias("nb"), F.col("x").alias("xb"))
    both = pairs.join(left, "a").join(right, "b").select("a", "b", "na", "nb", "xa", "xb")
    pair = "struct<l1:bigint,l2:bigint>"
    return both.mapInArrow(work, f"a long, b long, na {pair}, nb {pair}, like double")


def _middles(told: DataFrame) -> DataFrame:
    """(key, leader, other): of the lines (key, leader, lid, sketch) near a leader the one whose sketch is nearest to the bits that most of them have."""
    bit = lambda i: F.shiftrightunsigned("sketch", i).bitwiseAND(F.lit(1).cast("long"))
    counts = told.groupBy("key", "leader").agg(F.count("*").alias("n"), *(F.sum(bit(i)).alias(f"s{i}") for i in range(60)))
    most = sum((F.when(2 * F.col(f"s{i}") > F.col("n"), F.lit(1 << i).cast("long")).otherwise(F.lit(0).cast("long")) for i in range(1, 60)), F.when(2 * F.col("s0") > F.col("n"), F.lit(1).cast("long")).otherwise(F.lit(0).cast("long")))
    off = F.bit_count(F.col("sketch").bitwiseXOR(F.col("most")))
    return told.join(counts.select("key", "leader", most.alias("most")), ["key", "leader"]).groupBy("key", "leader").agg(F.min(F.struct(off.alias("off"), "lid")).alias("m")).select("key", "leader", F.col("m.lid").alias("other"))


def _alike(similar: float) -> F.Column:
    """Whether sizes and bit maps of two lines, (m, a0, ...) and (n, b0, ...), leave it open that they are similar."""
    share = Fraction(str(similar))
    p, q = share.numerator, share.denominator
    apart = sum((F.bit_count(F.col(f"a{i}").bitwiseXOR(F.col(f"b{i}"))) for i in range(MAPS)), F.lit(0))
    return (F.least("m", "n") * q >= F.greatest("m", "n") * p) & (apart * (q + p) <= (F.col("m") + F.col("n")) * (q - p))


def links(docs: DataFrame, similar: float = SIMILAR) -> DataFrame:
    """(node, component) of the lines, structs (l1, l2), that are similar to another: all similar lines of a bucket are in one component.

    Lines of a bucket are first compared with its leaders.  A line that is near a
    leader by sketch and similar to none is then compared with the middle of the
    lines near that leader, next with what is similar to that leader, if it is at least 1 - 2 (1 - similar) alike to it (distances of
    sets obey the triangle inequality, so no other line can be similar to both), and
    last with the other such lines of its bucket.  Lines of one component are not
    compared again, nor are those whose sizes or bit maps rule it out.
    """
    spark = docs.sparkSession
    met = stored(candidates(_band_keys(docs)), "candidates")
    release(spark)

    # every line that is compared later is in a first pair: the texts are fetched once
    pairs = stored(met.select(F.col("lid").alias("a"), F.col("leader").alias("b")).distinct(), "first-pairs")
    wanted = pairs.select(F.explode(F.array("a", "b")).alias("lid"))
    texts = stored(_texts(docs, wanted, 2 * pairs.count()), "line-texts")
    release(spark)

    def compared(pairs: DataFrame, label: str) -> DataFrame:
        out = stored(_compared(pairs, texts, SHINGLE), label)
        release(spark)
        return out

    def linked(found: DataFrame, before: DataFrame | None = None) -> DataFrame:
        """Components of the links found, and of those that were there before."""
        every = found.where(F.col("like") >= similar).select(F.col("na").alias("a"), F.col("nb").alias("b"))
        if before is not None:
            every = every.union(before.select(F.col("node").alias("a"), F.col("component").alias("b")))
        out = stored(components(every), "line-components")
        release(spark)
        return out

    def classes(rows: DataFrame, joined: DataFrame, lid: str, c: str) -> DataFrame:
        """With the class of a line: that of its component, or its own."""
        of = joined.select(F.col("node.l1").alias(lid), F.xxhash64("component").alias(f"{c}_"))
        return rows.join(of, lid, "left").withColumn(c, F.coalesce(f"{c}_", lid)).drop(f"{c}_")

    def mapped(rows: DataFrame, lid: str, n: str, cell: str) -> DataFrame:
        """With the sizes and bit maps of lines."""
        return rows.join(texts.select(F.col("l1").alias(lid), F.col("n").alias(n), *(F.col(c).alias(f"{cell}{i}") for i, c in enumerate(CELLS))), lid)

    def apart(pairs: DataFrame) -> DataFrame:
        return pairs.where(F.col("lid") != F.col("other")).select(F.greatest("lid", "other").alias("a"), F.least("lid", "other").alias("b"))

    first = compared(pairs, "line-pairs")
    joined = linked(first)
    told = met.join(first.select(F.col("a").alias("lid"), F.col("b").alias("leader"), "like"), ["lid", "leader"])
    told = stored(told.select("key", "lid", "sketch", "leader", "like"), "lines-told")
    release(spark)
    discard(met)
    best = told.groupBy("key", "lid").agg(F.max("like").alias("best")).where(F.col("best") < similar).select("key", "lid")
    told_alone = stored(told.join(best, ["key", "lid"]), "lines-not-told")
    # most copies of one line are like that line, if not like each other: the middle of a leader's lines is tried on the rest
    crowd = told_alone.groupBy("key", "leader").count().where(F.col("count") >= HUB)
    hubs = classes(_middles(told.join(crowd, ["key", "leader"], "left_semi")), joined, "other", "oc")
    tried = classes(told_alone, joined, "lid", "c").join(hubs, ["key", "leader"]).where("c != oc")
    tried = mapped(mapped(tried.select("lid", "other").distinct(), "lid", "m", "a"), "other", "n", "b").where(_alike(similar))
    tried = stored(apart(tried).distinct(), "line-middles")
    release(spark)
    if not tried.isEmpty():
        joined = linked(compared(tried, "line-hubs"), joined)
    alone = stored(classes(told_alone, joined, "lid", "c"), "lines-alone")
    close = (F.col("c") != F.col("oc")) & (F.bit_count(F.col("sketch").bitwiseXOR(F.col("osketch"))) <= APART) & _alike(similar)
    open_ = alone.where(F.col("like") >= 2 * similar - 1 - 1e-9)
    near = told.where(F.col("like") >= similar).join(open_.select("key", "leader").distinct(), ["key", "leader"], "left_semi")
    near = classes(near.select("key", F.col("lid").alias("other"), F.col("sketch").alias("osketch"), "leader"), joined, "other", "oc")
    both = mapped(open_, "lid", "m", "a").join(mapped(near, "other", "n", "b"), ["key", "leader"])
    gray = stored(apart(both.where(close)).distinct(), "line-gray")
    release(spark)
    if not gray.isEmpty():
        joined = linked(compared(gray, "line-more"), joined)
    rows = stored(classes(alone.select("key", "lid", "sketch").distinct(), joined, "lid", "c"), "lines-still-alone")
    crowd = rows.groupBy("key").count().where("count > 1").select("key")
    rows = rows.join(crowd, "key", "left_semi")
    peer = rows.select("key", F.col("lid").alias("other"), F.col("sketch").alias("osketch"), F.col("c").alias("oc"))
    both = mapped(rows, "lid", "m", "a").join(mapped(peer, "other", "n", "b"), "key")
    peers = stored(apart(both.where((F.col("lid") < F.col("other")) & close)).distinct(), "line-peers")
    release(spark)
    if not peers.isEmpty():
        joined = linked(compared(peers, "line-last"), joined)
    discard(texts, pairs, first, told)
    return joined


KEPT = T.StructType([T.StructField("n_lines", T.LongType(), False), T.StructField("n_removed", T.LongType(), False), T.StructField("kept", T.StringType(), False)])


def deduplicate(docs: DataFrame, ident: str = "doc_id", text: str = "text", similar: float = SIMILAR, digest: bool = False) -> DataFrame:
    """(ident, n_lines, n_removed, kept): each document without the lines that an earlier line is like.

    Earlier is by id, then by place in the document; null ids come last.  Blank
    lines always stay and are no part of n_removed.  Null texts have one blank
    line.  Repeated rows with one id and text are judged alike.  With `digest`
    kept is the SHA-256 of what is left.
    """
    spark, kind = docs.sparkSession, docs.schema[ident].dataType.simpleString()
    base = docs.select(quoted(ident).alias("id"), quoted(text).alias("text"), F.xxhash64(quoted(text)).alias("t"))
    root = links(base, similar).select("node.*", F.col("component").alias("c"))
    seen = stored(_occurrences(base), "lines")
    # of each component the first occurrence stays; t tells rows with one id apart
    rank = F.struct(F.col("id").isNull().alias("z"), F.col("id").alias("i"), F.col("at").alias("n"), "t")
    firsts = seen.groupBy("l1", "l2").agg(F.min(rank).alias("first"), F.count("*").alias("n"))
    # a line alone in its class has its own first occurrence, and matters only if there are others of it
    few = stored(firsts.join(root, ["l1", "l2"], "left").where("c is not null or n > 1"), "line-classes")
    release(spark)
    heads = few.where("c is not null").groupBy("c").agg(F.min("first").alias("head"))
    doomed = few.where("c is not null").join(heads, "c").select("l1", "l2", "head").union(few.where("c is null").select("l1", "l2", F.col("first").alias("head")))
    doomed = stored(doomed, "line-heads")
    release(spark)
    gone = seen.select("id", "t", "at", "l1", "l2").join(doomed, ["l1", "l2"]).where(rank != F.col("head")).groupBy("id", "t").agg(F.collect_set("at").alias("gone"))
    full = base.join(gone.withColumnRenamed("id", "gid").withColumnRenamed("t", "gt"), F.col("id").eqNullSafe(F.col("gid")) & (F.col("t") == F.col("gt")), "left")

    def work():
        def each(part):
            n, removed, kept = [], [], []
            for t, at in zip(part.column(part.schema.get_field_index("text")).to_pylist(), part.column(part.schema.get_field_index("gone")).to_pylist(), strict=True):
                rows, drop = (t or "").split("\n"), set(at or ())
                left = "\n".join([x for i, x in enumerate(rows) if i not in drop]) if drop else t or ""
                n.append(len(rows))
                removed.append(len(drop))
                kept.append(hashlib.sha256(left.encode()).hexdigest() if digest else left)
            return {"n_lines": n, "n_removed": removed, "kept": kept}

        return each

    made = append_struct(full.select("id", "text", "gone"), "s", KEPT, "text", work, keep=["id"])
    return made.select(F.col("id").cast(kind).alias(ident), "s.n_lines", "s.n_removed", F.col("s.kept").alias("kept"))
