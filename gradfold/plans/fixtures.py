"""Training tables derived from the given ones, each as a DataFrame and as DuckDB SQL."""

from __future__ import annotations

import hashlib
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import hashing as H
from ..functions import vectors as V
from ..sources.tables import table

D = 65


def catx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The one-dimensional example over all customers: x = [1]; y = 1 for an even nation, else -1."""
    return table(spark, sf_dir, "customer").select(F.col("c_custkey").cast("long").alias("id"), F.array(F.lit(1.0)).alias("x"), F.when(F.col("c_nationkey") % 2 == 0, 1.0).otherwise(-1.0).alias("y"))


SQL_CATX = "SELECT c_custkey::BIGINT AS id, CASE WHEN c_nationkey % 2 = 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM customer"


def emb_half(spark: SparkSession, sf_dir: str) -> DataFrame:
    """64 features and a bias; y = 1 for labels below 5."""
    x = F.array_append(F.col("embedding").cast("array<double>"), F.lit(1.0))
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("id"), x.alias("x"), F.when(F.col("label") < 5, 1.0).otherwise(-1.0).alias("y"))


SQL_EMB = "SELECT vec_id::BIGINT AS id, list_append(embedding::DOUBLE[], 1.0::DOUBLE) AS x, CASE WHEN label < 5 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM embeddings"


def emb_ovr(spark: SparkSession, sf_dir: str, c: int) -> DataFrame:
    x = F.array_append(F.col("embedding").cast("array<double>"), F.lit(1.0))
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("id"), x.alias("x"), F.when(F.col("label") == c, 1.0).otherwise(-1.0).alias("y"))


def tiny(spark: SparkSession, sf_dir: str) -> DataFrame:
    return emb_half(spark, sf_dir).where("id < 50")


SQL_TINY = f"SELECT * FROM ({SQL_EMB}) WHERE id < 50"


def standard(df: DataFrame, columns: list[str]) -> DataFrame:
    """Columns minus mean over population deviation; the statistics are one row, broadcast."""
    stats = df.agg(*(f(c).alias(f"{p}_{c}") for c in columns for p, f in (("m", F.avg), ("s", F.stddev_pop))))
    joined = df.crossJoin(F.broadcast(stats))
    scaled = {c: F.when(F.col(f"s_{c}") > 0, (F.col(c) - F.col(f"m_{c}")) / F.col(f"s_{c}")).otherwise(0.0) for c in columns}
    return joined.withColumns(scaled).select(*df.columns)


def line_dense(spark: SparkSession, sf_dir: str, copies: int = 1) -> DataFrame:
    """Four standardised columns of lineitem and a bias; y = 1 for returned rows.  `copies` repeats the table."""
    names = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    df = table(spark, sf_dir, "lineitem")
    df = standard(df.select(F.xxhash64(*df.columns).alias("id"), *(F.col(c).cast("double").alias(c) for c in names), "l_returnflag"), names)
    out = df.select("id", F.array(*names, F.lit(1.0)).alias("x"), F.when(F.col("l_returnflag") == "R", 1.0).otherwise(-1.0).alias("y"))
    if copies > 1:
        out = out.select(F.explode(F.sequence(F.lit(1), F.lit(copies))).alias("c"), "*").select(F.xxhash64("id", "c").alias("id"), "x", "y")
    return out


def part_price(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A regression that can be learnt: the retail price from the key's last digits and the size."""
    df = table(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("id"), (F.col("p_partkey") % 1000).cast("double").alias("a"), F.col("p_size").cast("double").alias("b"), F.col("p_retailprice").cast("double").alias("c"))
    return standard(df, ["a", "b", "c"]).select("id", F.array("a", "b", F.lit(1.0)).alias("x"), F.col("c").alias("y"))


SQL_PART = """SELECT id, [(a - avg(a) OVER ()) / stddev_pop(a) OVER (), (b - avg(b) OVER ()) / stddev_pop(b) OVER (), 1.0::DOUBLE] AS x,
  (c - avg(c) OVER ()) / stddev_pop(c) OVER () AS y
  FROM (SELECT p_partkey::BIGINT AS id, (p_partkey % 1000)::DOUBLE AS a, p_size::DOUBLE AS b, p_retailprice::DOUBLE AS c FROM part)"""

_UP, _LOW = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
FEATURES = 65536


def tokens(spark: SparkSession, sf_dir: str, name: str = "documents", ident: str = "doc_id") -> DataFrame:
    """(id, token): ASCII words of a text column, lower-cased."""
    words = F.split(F.translate("text", _UP, _LOW), "[^a-z]+")
    return table(spark, sf_dir, name).select(F.col(ident).cast("long").alias("id"), F.explode(words).alias("token")).where("token != ''")


SQL_TOKENS = f"SELECT id, token FROM (SELECT doc_id::BIGINT AS id, unnest(regexp_split_to_array(translate(text, '{_UP}', '{_LOW}'), '[^a-z]+')) AS token FROM documents) WHERE token != ''"


def doc_sparse(spark: SparkSession, sf_dir: str, labelled: bool = True) -> DataFrame:
    """(id, feature, value, y): hashed term frequencies; y by quality label, or by language if not `labelled`."""
    counted = tokens(spark, sf_dir).select("id", (H.number(1, F.col("token")) % FEATURES).alias("feature")).groupBy("id", "feature").agg(F.count("*").alias("n"))
    size = counted.groupBy("id").agg(F.sum("n").alias("size"))
    if labelled:
        y = table(spark, sf_dir, "labels").select(F.col("doc_id").cast("long").alias("id"), F.when(F.col("quality") == 1, 1.0).otherwise(-1.0).alias("y"))
    else:
        y = table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("id"), F.when(F.col("lang") == "en", 1.0).otherwise(-1.0).alias("y"))
    return counted.join(size, "id").join(y, "id").select("id", "feature", (F.col("n") / F.col("size")).alias("value"), "y")


SQL_SPARSE = f"""SELECT c.id, feature, n / size AS value, y FROM (
    SELECT id, {H.sql_number("1", "token")} % {FEATURES} AS feature, count(*)::DOUBLE AS n FROM ({SQL_TOKENS}) GROUP BY 1, 2) c
  JOIN (SELECT id, count(*)::DOUBLE AS size FROM ({SQL_TOKENS}) GROUP BY 1) s USING (id)
  JOIN (SELECT doc_id::BIGINT AS id, CASE WHEN quality = 1 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END AS y FROM labels) USING (id)"""


def sparse_rows(cells: DataFrame) -> DataFrame:
    """(id, idx, val, y): the cells of each row as two arrays in the order of features."""
    rows = cells.groupBy("id", "y").agg(F.sort_array(F.collect_list(F.struct("feature", "value"))).alias("c"))
    return rows.select("id", F.col("c.feature").alias("idx"), F.col("c.value").alias("val"), "y")


class _Cells(dict):
    """The cell of each word met: its feature modulo `d`."""

    def __init__(self, d: int):
        self.d = d

    def __missing__(self, word: bytes) -> int:
        self[word] = cell = int.from_bytes(hashlib.md5(b"1:" + word).digest()[:4], "big") % FEATURES % self.d
        return cell


def doc_dense(spark: SparkSession, sf_dir: str, d: int = D - 1) -> DataFrame:
    """`d` shares of hashed words and a bias, scaled to a norm near one; y = 1 for English: a set that can be learnt.

    The words and features of `doc_sparse`, counted where a document is read: a row is exchanged for each document, not for each of its words.
    """

    def work(batches):
        cells, word = _Cells(d), re.compile(rb"[a-z]+")
        for batch in batches:
            found = [[cells[w] for w in word.findall(t.lower())] if t else [] for t in batch.column(2).cast(pa.binary()).to_pylist()]
            n = [np.bincount(np.array(f, np.int64), minlength=d) for f in found]
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(n) + 1, dtype=np.int32) * d), pa.array(np.concatenate(n) if n else np.zeros(0, np.int64)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([len(f) for f in found], pa.int64()), lists], names=["id", "y", "size", "n"])
            if len(cells) > 1 << 20:
                cells.clear()

    docs = table(spark, sf_dir, "documents").where("doc_id is not null").select(F.col("doc_id").cast("long").alias("id"), F.when(F.col("lang") == "en", 1.0).otherwise(-1.0).alias("y"), "text")
    counted = docs.mapInArrow(work, "id long, y double, size long, n array<long>")
    # rows of one id are one document for each of their classes, once for each row
    sums = F.array(*(F.sum(F.col("n")[j]) for j in range(d)))
    each = counted.groupBy("id").agg(sums.alias("n"), F.sum("size").alias("size"), F.count_if(F.col("y") > 0).alias("p"), F.count_if(F.col("y") < 0).alias("q"))
    sides = F.explode(F.array(F.struct(F.lit(1.0).alias("y"), F.col("p").alias("m")), F.struct(F.lit(-1.0).alias("y"), F.col("q").alias("m"))))
    each = each.where("size > 0").select("id", "n", "size", sides.alias("c")).where("c.m > 0")
    x = F.transform("n", lambda v: 4.0 * F.col("c.m") * v / F.col("size"))
    return each.select("id", F.array_append(x, F.lit(1.0)).alias("x"), F.col("c.y").alias("y"))


def ratings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(i, j, m): mean quantity of a part in a customer's orders, over 50."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.groupBy(F.col("o_custkey").cast("long").alias("i"), F.col("l_partkey").cast("long").alias("j")).agg((F.avg("l_quantity") / 50).alias("m"))


SQL_RATINGS = "SELECT o_custkey::BIGINT AS i, l_partkey::BIGINT AS j, avg(l_quantity) / 50 AS m FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2"


def rank4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells with a planted rank of 4: inner products of four components, over a hashed sample of pairs.

    Every row meets only the partners that a hash of the pair names, out of the sampled ids; ids are at most a few thousand.
    """
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long").alias("id"), F.slice(F.col("embedding").cast("array<double>"), 1, 4).alias("f"))
    a, b = e.select(F.col("id").alias("i"), F.col("f").alias("fi")), e.select(F.col("id").alias("j"), F.col("f").alias("fj"))
    pairs = a.join(b, F.col("i") < F.col("j")).where(H.number(42, F.col("i"), F.col("j")) % 50 == 0)
    return pairs.select("i", "j", (V.dot(F.col("fi"), F.col("fj")) * 64).alias("m"))


def small_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(k, i, j, m): lineitem hashed to 5 x 7 cells."""
    df = table(spark, sf_dir, "lineitem").groupBy((F.col("l_suppkey") % 5).cast("int").alias("i"), (F.col("l_partkey") % 7).cast("int").alias("j")).agg((F.avg("l_quantity") / 50).alias("m"))
    return df.select(H.order_key(42, F.col("i"), F.col("j")).alias("k"), "i", "j", F.round("m", 9).alias("m"))


SQL_CELLS = f"SELECT {H.sql_key('42', 'i', 'j')} AS k, i, j, round(m, 9) AS m FROM (SELECT (l_suppkey % 5)::INT AS i, (l_partkey % 7)::INT AS j, avg(l_quantity) / 50 AS m FROM lineitem GROUP BY 1, 2)"


def dialogs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(k, seq_id, feats, tags): the turns of a conversation; features 0 bias, 1-10 length bucket, 11-13 last character's class."""
    length = F.least(F.floor(F.length("text") / 50), F.lit(9)).cast("int") + 1
    last = F.substring("text", -1, 1)
    kind = F.when(last.isin(".", "!"), 11).when(last == "?", 12).otherwise(13)
    tag = F.when(F.col("role") == "system", 0).when(F.col("role") == "user", 1).otherwise(2)
    turn = F.struct("turn", F.array(F.lit(0), length, kind).alias("f"), tag.alias("g"))
    seqs = table(spark, sf_dir, "conversations").where("text is not null").groupBy("conv_id").agg(F.sort_array(F.collect_list(turn)).alias("t"))
    return seqs.select(H.order_key(42, F.col("conv_id")).alias("k"), F.col("conv_id").cast("string").alias("seq_id"), F.col("t.f").alias("feats"), F.col("t.g").alias("tags"))


#: What a byte is to `chunks`: 0 of a word, 1 white space, 2 between sentences.
_KIND = np.array([2 if c in b".!?\n" else 1 if c in b" \t\x0b\f\r" else 0 for c in range(256)], np.uint8)
_FOLD = np.array([c + 32 if 65 <= c <= 90 else c for c in range(256)], np.uint8)


class _Hashes(dict):
    """Four features of each word met: as it is, as the one before, as the one after, by its ending; Spark's `xxhash64` of (kind, word) modulo `features`."""

    def __init__(self, features: int):
        self.features = features
        self.seeds = [xxhash.xxh64_intdigest(kind.to_bytes(4, "little"), 42) for kind in (1, 2, 3, 4)]

    def __missing__(self, word: bytes) -> list[int]:
        parts = (word, word, word, word.decode()[-2:].encode())
        found = [xxhash.xxh64_intdigest(w, s) for w, s in zip(parts, self.seeds, strict=True)]
        self[word] = found = [(h - (h >> 63 << 64)) % self.features for h in found]
        return found


def _whole_ids(batches, limit: int = 1 << 18):
    """Slices of (id, text), sorted by id, with about `limit` bytes of text and all rows of each of their ids, and where ids begin in them."""

    def cut(held: list):
        rows = pa.Table.from_batches(held).combine_chunks().to_batches()[0]
        codes = rows.column(0).dictionary_encode(null_encoding="encode").indices.to_numpy()
        first = np.flatnonzero(np.append(True, codes[1:] != codes[:-1]))
        ends = np.cumsum(pc.binary_length(rows.column(1)).fill_null(0).to_numpy().astype(np.int64))
        part = np.append(0, ends)[first] // limit
        cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), len(first)]
        for i, j in zip(cuts, cuts[1:], strict=False):
            lo, hi = int(first[i]), int(first[j]) if j < len(first) else rows.num_rows
            yield rows.slice(lo, hi - lo), first[i:j] - lo

    held = []
    for batch in batches:
        if not batch.num_rows:
            continue
        ids = batch.column(0)
        if held and held[-1].column(0)[-1] != ids[0]:
            yield from cut(held)
            held = []
        codes = ids.dictionary_encode(null_encoding="encode").indices.to_numpy()
        last = int(np.append(0, np.flatnonzero(codes[1:] != codes[:-1]) + 1)[-1])  # where the last id begins: it may go on
        if last:
            yield from cut([*held, batch.slice(0, last)])
            held = []
        held.append(batch.slice(last))
    if held:
        yield from cut(held)


def _spans(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """All places of runs that begin at `first`, one run after the other."""
    return np.repeat(first - (np.cumsum(size) - size), size) + np.arange(int(size.sum()))


def _chunked(rows: pa.RecordBatch, first: np.ndarray, hashes: _Hashes, most: int) -> pa.RecordBatch:
    """The sequences of `chunks` from all documents of some ids; an id's documents begin at `first`."""
    texts = rows.column(1).fill_null("").cast(pa.large_binary())
    offs = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
    data = _FOLD[np.frombuffer(texts.buffers()[2] or b"", np.uint8)[offs[0] : offs[-1]]]
    offs = offs - offs[0]
    kind = _KIND[data]
    # words, and the breaks between sentences, are runs of bytes of a kind inside a document
    begin = np.ones(len(data), bool)
    begin[1:] = kind[1:] != kind[:-1]
    begin[offs[(offs > 0) & (offs < len(data))]] = True
    runs = np.flatnonzero(begin)
    kinds, sizes = kind[runs], np.diff(np.append(runs, len(data)))
    breaks = np.cumsum(kinds == 2)
    here = kinds == 0
    start, size = runs[here], sizes[here]
    doc = np.searchsorted(offs, start, "right") - 1
    before = np.append(0, breaks)[np.searchsorted(runs, offs[:-1])]  # breaks before a document
    n = breaks[here] - before[doc]
    cuts = np.append(0, np.cumsum(size)).astype(np.int32)
    coded = pa.Array.from_buffers(pa.binary(), len(size), [None, pa.py_buffer(cuts), pa.py_buffer(data[kind == 0])]).dictionary_encode()
    words, code = coded.dictionary.to_pylist(), coded.indices.to_numpy()
    each = np.array([hashes[w] for w in words], np.int64).reshape(-1, 4)

    # sentences of two words or more, as runs of words
    fresh = np.ones(len(doc), bool)
    fresh[1:] = (doc[1:] != doc[:-1]) | (n[1:] != n[:-1])
    s_first = np.flatnonzero(fresh)
    s_size = np.diff(np.append(s_first, len(doc)))
    s_first, s_size = s_first[s_size > 1], s_size[s_size > 1]
    s_n, s_id = n[s_first], np.searchsorted(first, doc[s_first], "right") - 1
    documents = np.diff(np.append(first, len(texts)))
    if (documents > 1).any():  # the sentences of an id's documents by their number, then by words and tags
        order = np.arange(len(s_first))
        for i in np.flatnonzero(documents > 1).tolist():
            lo, hi = np.searchsorted(s_id, [i, i + 1]).tolist()

            def key(s: int):
                own = [words[c] for c in code[s_first[s] : s_first[s] + s_size[s]].tolist()]
                return int(s_n[s]), [(w, 0 if not j else 2 if j == len(own) - 1 else 1) for j, w in enumerate(own)]

            order[lo:hi] = sorted(range(lo, hi), key=key)
        s_first, s_size, s_n, s_id = (x[order] for x in (s_first, s_size, s_n, s_id))
    token = code[_spans(s_first, s_size)]
    ends = np.cumsum(s_size)
    tags = np.ones(len(token), np.int32)
    tags[ends - s_size], tags[ends - 1] = 0, 2

    # blocks of four sentences, cut to sequences
    fresh = np.ones(len(s_n), bool)
    fresh[1:] = (s_id[1:] != s_id[:-1]) | (s_n[1:] // 4 != s_n[:-1] // 4)
    b_first = (ends - s_size)[fresh]
    b_size = np.diff(np.append(b_first, len(token)))
    pieces = -(-b_size // most)
    of = np.repeat(np.arange(len(b_first)), pieces)
    p = _spans(np.zeros(len(pieces), np.int64), pieces)
    q_first = b_first[of] + p * most
    q_last = np.append(q_first, len(token))[1:] - 1
    h = each[token]
    feats = np.empty((len(token), 4), np.int32)
    feats[:, 0], feats[:, 3] = h[:, 0], h[:, 3]
    feats[1:, 1], feats[:-1, 2] = h[:-1, 1], h[1:, 2]
    feats[q_first, 1], feats[q_last, 2] = hashes[b"<"][1], hashes[b">"][2]
    four = pa.ListArray.from_arrays(pa.array(np.arange(len(token) + 1, dtype=np.int32) * 4), pa.array(feats.ravel()))
    bounds = pa.array(np.append(q_first, len(token)).astype(np.int32))
    ids = rows.column(0).take(pa.array(first[s_id[fresh]][of]))
    cols = [ids, pa.array((s_n[fresh] // 4)[of], pa.int64()), pa.array(p.astype(np.int32)), pa.ListArray.from_arrays(bounds, four), pa.ListArray.from_arrays(bounds, pa.array(tags))]
    return pa.RecordBatch.from_arrays(cols, names=["doc_id", "b", "p", "feats", "tags"])


def chunks(spark: SparkSession, sf_dir: str, features: int = 1 << 14, most: int = 64) -> DataFrame:
    """(k, seq_id, feats, tags): four joined sentences, in consecutive sequences of at most `most` tokens, tags first / inside / last; features are hashes of the word, its neighbours and its ending.

    Sentences are what stands between runs of `.`, `!`, `?` and line ends, words what
    stands between ASCII white space, with A-Z lower-cased; sentences of one word are
    left out but counted.  Documents of one id are joined sentence by sentence.
    """

    def work(batches):
        hashes = _Hashes(features)
        for rows, first in _whole_ids(batches):
            yield _chunked(rows, first, hashes, most)
            if len(hashes) > 1 << 17:
                hashes.clear()

    docs = table(spark, sf_dir, "documents").where("text is not null").select("doc_id", "text").repartition("doc_id").sortWithinPartitions("doc_id")
    made = docs.mapInArrow(work, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, b long, p int, feats array<array<int>>, tags array<int>")
    return made.select(H.fast(42, F.col("doc_id"), F.col("b"), F.col("p")).alias("k"), F.concat_ws(":", "doc_id", "b", "p").alias("seq_id"), "feats", "tags")


def daily(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(t, y): the mean value of events on day t."""
    days = table(spark, sf_dir, "events").groupBy(F.to_date("ts").alias("d")).agg(F.avg("value").alias("y"))
    return days.select(F.row_number().over(Window.orderBy("d")).alias("t"), "y")


SQL_DAILY = "SELECT row_number() OVER (ORDER BY d)::INT AS t, y FROM (SELECT ts::DATE AS d, avg(value) AS y FROM events GROUP BY 1)"


def returns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(t, a, r): month-on-month change of the mean order value of each market segment, for months that all segments have."""
    orders = table(spark, sf_dir, "orders").select("o_custkey", "o_totalprice", F.date_format("o_orderdate", "yyyy-MM").alias("t"))
    joined = orders.join(table(spark, sf_dir, "customer").select("c_custkey", F.col("c_mktsegment").alias("a")), F.col("o_custkey") == F.col("c_custkey"))
    means = joined.groupBy("t", "a").agg(F.avg("o_totalprice").alias("v"))
    full = means.groupBy("t").agg(F.count("*").alias("n")).where("n = 5").select("t")
    change = F.col("v") / F.lag("v").over(Window.partitionBy("a").orderBy("t")) - 1
    return means.join(full, "t").select("t", "a", change.alias("r")).where("r is not null")


SQL_RETURNS = """SELECT t, a, r FROM (SELECT t, a, v / lag(v) OVER (PARTITION BY a ORDER BY t) - 1 AS r FROM (
    SELECT t, a, v, count(*) OVER (PARTITION BY t) AS n FROM (
      SELECT strftime(o_orderdate, '%Y-%m') AS t, c_mktsegment AS a, avg(o_totalprice) AS v FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2)) WHERE n = 5) WHERE r IS NOT NULL"""
