"""SimHash near-duplicates with pigeonring filtering.

A fingerprint is a ring of `SEGMENTS` segments.  If two fingerprints differ in at
most `most` bits, then from some segment on every chain of consecutive segments
keeps within its proportional budget: the first l segments of the ring from there
differ in at most l * most / SEGMENTS bits together.  The first two links of that
chain are an equi-join key - one segment equal and the next one within one bit,
enumerated on one side - and the rest of the ring is tested before the full
Hamming distance.  With a key of 32 bits a bucket stays small while the corpus
grows.  Distinct fingerprints are joined, not documents: copies never meet.

Buckets with more than `dense` fingerprints (very large groups of near copies)
are linked by another exact way: two fingerprints are within two bits of each
other exactly if they share a fingerprint within one bit of both, so every member
is dealt to the 65 fingerprints around it and linked to the least of each.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels
from .components import components
from .shared import apart, append_struct, free_name, quoted, stored

SHINGLE, SEED, MOST = 3, 42, 2
SEGMENTS, BITS = 4, 16
DENSE = 2048

FIELDS = T.StructType([T.StructField("bits", T.LongType(), False)])


def fingerprint(words: list[bytes], shingle: int = SHINGLE) -> int:
    """The fingerprint of a sequence of words; 0 without words."""
    if not words:
        return 0
    n = max(1, len(words) - shingle + 1)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    whole, digest = b" ".join(words), xxhash.xxh64_intdigest
    last = ends[shingle - 1 :] if len(words) >= shingle else ends[-1:]
    h = np.fromiter([digest(whole[a:b], SEED) for a, b in zip(starts[:n].tolist(), last.tolist(), strict=True)], np.uint64, n)
    counts = np.zeros(64, np.int64)
    lanes = np.uint64(0x0101010101010101)
    for at in range(0, n, 255):  # a byte counts up to 255
        part = h[at : at + 255]
        for bit in range(8):
            counts[bit::8] += (part >> np.uint64(bit) & lanes).sum(dtype=np.uint64).reshape(1).view(np.uint8)
    return sum(1 << i for i, c in enumerate(counts.tolist()) if 2 * c > n)


def fingerprints(docs: DataFrame, text: str = "text", into: str = "simhash", keep: list[str] | None = None) -> DataFrame:
    """All rows and columns with a struct `into` whose `bits` is the fingerprint as a signed long.

    Words are what stands between ASCII white space, with A-Z lower-cased; a
    fingerprint bit is set if it is set in over half of the hashes of all
    three-word shingles.  Fewer words than a shingle are one shingle; no words
    (empty, blank or null text) give 0.
    """

    def work():
        def each(part):
            data, offs = kernels.text_bytes(part.column(part.schema.get_field_index(text)))
            raw, cuts = data.tobytes(), offs.tolist()
            bits = [fingerprint(raw[a:b].lower().split()) for a, b in zip(cuts, cuts[1:], strict=False)]
            return {"bits": pa.array(np.array(bits, np.uint64).view(np.int64))}

        return each

    return append_struct(docs, into, FIELDS, text, work, keep)


def _segment(c: F.Column, i: int) -> F.Column:
    return F.shiftrightunsigned(c, BITS * (i % SEGMENTS)).bitwiseAND(F.lit((1 << BITS) - 1).cast("long"))


def _distance(a: F.Column, b: F.Column) -> F.Column:
    return F.bit_count(a.bitwiseXOR(b))


def _ring_key(c: F.Column, i: int, flip: int = 0) -> F.Column:
    """Start i of the ring with its segment and the next one, of which `flip` bits are changed."""
    following = _segment(c, i + 1).bitwiseXOR(F.lit(flip).cast("long"))
    return F.lit(i << 2 * BITS).cast("long") + F.shiftleft(_segment(c, i), BITS) + following


def links(prints: DataFrame, most: int = MOST, dense: int = DENSE) -> DataFrame:
    """Pairs (a, b) of distinct values in column `bits` that differ in at most `most` bits.

    Every pair is given directly, or, among members of dense buckets, through a
    common smallest neighbour within one bit; components are the same either way.
    """
    if not 0 <= most <= 2:
        raise ValueError("the ring is laid out for at most two differing bits")
    flips = [0, *(1 << i for i in range(BITS))]
    bits = F.col("bits")
    probe = stored(prints.select(bits.alias("a"), F.explode(F.array(*(_ring_key(bits, i) for i in range(SEGMENTS)))).alias("k")), "ring-probe")
    store = prints.select(bits.alias("b"), F.explode(F.array(*(_ring_key(bits, i, f) for i in range(SEGMENTS) for f in flips))).alias("k"))
    full = stored(probe.groupBy("k").count().where(F.col("count") > dense).select("k"), "dense-keys")
    # chains of three and of four links, from the start that the key names; every chain is within its budget before the full check
    a, b = F.col("a"), F.col("b")
    start = F.shiftright("k", 2 * BITS).cast("int")
    third = F.coalesce(*(F.when(start == i, sum((_distance(_segment(a, i + j), _segment(b, i + j)) for j in range(3)), F.lit(0))) for i in range(SEGMENTS)))
    near = (a < b) & (third <= 3 * most // SEGMENTS) & (_distance(a, b) <= most)
    near |= (a > b) & (third <= 3 * most // SEGMENTS) & (_distance(a, b) <= most)
    many = full.count()
    if not many:
        return probe.join(apart(store), "k").where(near).select("a", "b")
    pairs = probe.join(apart(full), "k", "left_anti").join(apart(store), "k").where(near).select("a", "b")
    crowd = store.join(apart(full), "k", "left_semi").select(F.col("b").alias("bits")).distinct()
    around = crowd.select(bits.alias("b"), F.explode(F.array(bits, *(bits.bitwiseXOR(F.lit(1 << i if i < 63 else -(1 << 63)).cast("long")) for i in range(64)))).alias("k"))
    if most < 2:  # a shared neighbour means two bits; only those at hand are meant then
        return pairs.union(around.join(apart(crowd.select(bits.alias("a"))), F.col("a") == F.col("k")).where((a != b) & (_distance(a, b) <= most)).select("a", "b"))
    around = stored(around, "around")
    least = around.groupBy("k").agg(F.min("b").alias("a"), F.count("*").alias("n")).where("n > 1").select("k", "a")
    return pairs.union(around.join(apart(least), "k").where(a != b).select("a", "b"))


def classes(prints: DataFrame, ident: str, most: int = MOST, dense: int = DENSE) -> DataFrame:
    """(bits, component_id) for every distinct fingerprint; component_id is the smallest `ident` in its class.

    Rows whose `ident` is null take part; a class of only such rows has a null component_id.
    """
    each = stored(prints.groupBy("bits").agg(F.min(quoted(ident)).alias("first")), "prints")
    joined = components(links(each, most, dense))
    both = each.join(apart(joined), each.bits == joined.node, "left").select("bits", "first", F.coalesce("component", "bits").alias("c"))
    both = stored(both, "classes")
    roots = both.groupBy("c").agg(F.min("first").alias("component_id"))
    return stored(both.join(apart(roots), "c").select("bits", "component_id"), "class-ids")


def near_duplicates(docs: DataFrame, ident: str = "doc_id", text: str = "text", most: int = MOST, dense: int = DENSE) -> DataFrame:
    """(ident, fingerprint, component_id), one row for each row of `docs`.

    Links are fingerprints with `most` or fewer differing bits; component_id is
    the smallest id reachable over links.  Empty and null texts have fingerprint
    zero and link like others; repeated rows come out as often as they come in.
    """
    out = ident
    base = docs.select(quoted(ident).alias("i"), quoted(text).alias("t"))
    prints = stored(fingerprints(base, "t", "s", keep=["i"]).select("i", F.col("s.bits").alias("bits")), "fingerprints")
    found = classes(prints, "i", most, dense)
    return prints.join(apart(found), "bits").select(F.col("i").alias(out), F.lower(F.lpad(F.hex("bits"), 16, "0")).alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame, ident: str = "doc_id", text: str = "text", most: int = MOST) -> DataFrame:
    """The rows of `docs`, of each near-duplicate class only one: that with the smallest id, and of ties one with the smallest text digest.

    All columns are kept.  Rows without an id are their classes' last choice.
    """
    order = F.struct(quoted(ident).isNull().alias("z"), quoted(ident).alias("i"), F.sha2(F.coalesce(quoted(text), F.lit("")), 256).alias("d"))
    into, mark = free_name(docs, "simhash"), free_name(docs, "rank")
    prints = stored(fingerprints(docs.select(order.alias(mark), quoted(text).alias(text)), text, into, keep=[mark]).select(mark, F.col(f"{into}.bits").alias("bits")), "fingerprints")
    reps = prints.groupBy("bits").agg(F.min(mark).alias(mark))
    found = classes(reps.select("bits", F.col(mark).alias("m")), "m", most)
    won = free_name(docs, "winner")
    winners = found.select(F.col("component_id").alias(won)).distinct()
    return winners_only(docs, order, mark, prints, winners, won)


def winners_only(docs: DataFrame, order: F.Column, mark: str, prints: DataFrame, winners: DataFrame, won: str) -> DataFrame:
    """The rows of `docs` whose `order` is among the winners; `prints` has it for every row as `mark`."""
    mine = F.col(mark) == F.col(won)
    kept = docs.withColumn(mark, order).join(apart(winners), mine, "left_semi")
    # rows that tie in id and text are copies of one row: one stays
    twice = stored(prints.groupBy(mark).count().where("count > 1").join(apart(winners), mine, "left_semi").select(F.col(mark).alias(won)), "ties")
    if twice.isEmpty():
        return kept.select(*docs.columns)
    return kept.join(apart(twice), mine, "left_anti").union(kept.join(apart(twice), mine, "left_semi").dropDuplicates([mark])).select(*docs.columns)
