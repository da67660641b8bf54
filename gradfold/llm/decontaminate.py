"""Benchmark decontamination by a prefix-filtered set join.

A window is `window` consecutive words of a benchmark item, and a document holds
it when it holds those words in that order.  As a set of word shingles a window
is contained in a document only if its *rarest* shingle is, so one shingle - the
necessary prefix under an order by rarity in the corpus - is enough to find all
candidates.  The offset of that shingle in its window gives the one place where
the window can begin (positional bound), the document's words give whether it
fits (length bound), and what is left is compared word by word.

Two passes over the documents, no shuffle of text: one counts the benchmark's
shingles in the corpus, one joins and verifies.  The benchmark is cut into blocks
of a fixed size, so what a task holds does not grow with it.
"""

from __future__ import annotations

import hashlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from . import kernels
from .shared import append_struct, free_name, quoted, stored

WINDOW, SHINGLE = 10, 3
#: Bytes of benchmark text in one block; its index takes some tens of times that in each Python worker.
BLOCK_BYTES = 4 << 20
#: Bytes of text that are hashed at a time: arrays of eight bytes for each of them are made, several at once.
PART_BYTES = 1 << 18

SCAN = T.StructType(
    [
        T.StructField("n_words", T.LongType(), False),
        T.StructField("spans", T.ArrayType(T.LongType(), False), False),
        T.StructField("items", T.ArrayType(T.StringType(), False), False),
    ]
)


RESULT = T.StructType(
    [
        T.StructField("n_words", T.LongType(), False),
        T.StructField("n_hit", T.LongType(), False),
        T.StructField("n_items", T.LongType(), False),
        T.StructField("items", T.ArrayType(T.StringType(), False), False),
        T.StructField("items_sha256", T.StringType(), False),
        T.StructField("contaminated", T.BooleanType(), False),
    ]
)


def summary(n_words: list[int], spans: list[list[int]], items: list[list[str]]) -> dict:
    """The measures of documents from the windows found in them (start and length in turn)."""
    hit = []
    for s in spans:
        covered, upto = 0, 0
        for a, n in sorted(zip(s[::2], s[1::2], strict=True)):
            covered += max(0, a + n - max(a, upto))
            upto = max(upto, a + n)
        hit.append(covered)
    return {"n_words": n_words, "n_hit": hit, "n_items": [len(x) for x in items], "items": items, "items_sha256": [hashlib.sha256(",".join(x).encode()).hexdigest() for x in items], "contaminated": [h > 0 for h in hit]}


class Block:
    """The windows of some benchmark items, with their shingles' hashes."""

    def __init__(self, items: list[tuple[str, str]], window: int, shingle: int):
        data, offs = kernels.text_bytes(pa.array([t for _, t in items], pa.large_string()))
        words = kernels.alnum_words(data, offs)
        hashes = words.hashes()
        self.key: dict[tuple[int, bytes], int] = {}
        owners: list[set[str]] = []
        self.size: list[int] = []
        rows: dict[int, list[tuple[int, int, int]]] = defaultdict(list)
        runs = {k: words.runs(k, hashes) for k in range(1, shingle + 1)}
        at = {k: dict(zip(b.tolist(), h.tolist(), strict=True)) for k, (b, h) in runs.items()}
        spelt = [words.data[s:e].tobytes() for s, e in zip(words.starts.tolist(), words.ends.tolist(), strict=True)]
        for i, (name, _) in enumerate(items):
            first, last = int(words.first[i]), int(words.first[i + 1])
            size = min(window, last - first)
            for start in range(first, last - size + 1) if size else ():
                text = b" ".join(spelt[start : start + size])
                w = self.key.setdefault((size, text), len(owners))
                if w == len(owners):
                    owners.append(set())
                    self.size.append(size)
                    k = min(shingle, size)
                    rows[k] += [(w, o, at[k][start + o]) for o in range(size - k + 1)]
                owners[w].add(name)
        self.owners = [sorted(o) for o in owners]
        self.shingles = {k: tuple(np.array(c, t) for c, t in zip(zip(*r, strict=True), (np.int64, np.int64, np.uint64), strict=True)) for k, r in rows.items()}

    def distinct(self) -> dict[int, np.ndarray]:
        return {k: np.unique(h) for k, (_, _, h) in self.shingles.items()}

    def prefixes(self, counts: dict[tuple[int, int], int]) -> dict[int, tuple]:
        """For each shingle length: sorted rarest shingles, and the windows and offsets that each stands for."""
        out = {}
        for k, (window, offset, h) in self.shingles.items():
            n = np.array([counts.get((k, int(x)), 0) for x in h])
            order = np.lexsort((offset, n, window))
            pick = order[np.unique(window[order], return_index=True)[1]]
            pick = pick[np.argsort(h[pick], kind="stable")]
            members, begin = np.unique(h[pick], return_index=True)
            out[k] = (members, np.append(begin, len(pick)), window[pick], offset[pick])
        return out


def _tally(batches, text: str, distinct: dict[int, np.ndarray]):
    """(k, h, n): how often each benchmark shingle stands in the texts of some batches, in memory for one part of a batch."""
    probes = {k: kernels.Probe(m) for k, m in distinct.items()}
    total = {k: np.zeros(len(m), np.int64) for k, m in distinct.items()}
    for batch in batches:
        for part in kernels.slices(batch, text, PART_BYTES):
            words = kernels.alnum_words(*kernels.text_bytes(part.column(0)))
            hashes = words.hashes()
            for k, probe in probes.items():
                _, where = probe.find(words.runs(k, hashes)[1])
                total[k] += np.bincount(where, minlength=len(total[k]))
    for k, n in total.items():
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), k, np.int32)), pa.array(distinct[k][at].view(np.int64)), pa.array(n[at])], names=["k", "h", "n"])


def _counted(docs: DataFrame, text: str, distinct: dict[int, np.ndarray]) -> dict[tuple[int, int], int]:
    """How often each benchmark shingle stands in all documents."""

    def run(batches):
        return _tally(batches, text, distinct)

    found = docs.select(quoted(text).alias(text)).mapInArrow(run, "k int, h long, n long").groupBy("k", "h").agg(F.sum("n").alias("n"))
    return {(k, h & (1 << 64) - 1): n for k, h, n in found.collect()}  # bounded by the block's shingles


def _scan(docs: DataFrame, text: str, block: Block, prefixes: dict, into: str, keep: list[str], final: bool = False) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast((prefixes, block.size, block.key, block.owners))

    def work():
        table, size, key, owners = shared.value
        probes = {k: kernels.Probe(v[0]) for k, v in table.items()}
        length = np.array(size, np.int64)

        def each(part):
            words = kernels.alnum_words(*kernels.text_bytes(part.column(part.schema.get_field_index(text))))
            hashes, counts = words.hashes(), words.counts
            doc_of = np.repeat(np.arange(len(counts)), counts)
            spans = [[] for _ in range(len(counts))]
            items = [set() for _ in range(len(counts))]
            for k, probe in probes.items():
                begin, h = words.runs(k, hashes)
                at, which = probe.find(h)
                if not len(at):
                    continue
                _, head, window, offset = table[k]
                many = head[which + 1] - head[which]
                flat = np.repeat(head[which] - np.cumsum(many) + many, many) + np.arange(many.sum())
                start = np.repeat(begin[at], many) - offset[flat]
                doc = doc_of[np.repeat(begin[at], many)]
                window = window[flat]
                fits = (start >= words.first[doc]) & (start + length[window] <= words.first[doc + 1])
                for s, d, w in zip(start[fits].tolist(), doc[fits].tolist(), window[fits].tolist(), strict=True):
                    n = size[w]
                    spelt = b" ".join([words.data[a:b].tobytes() for a, b in zip(words.starts[s : s + n].tolist(), words.ends[s : s + n].tolist(), strict=True)])
                    if key.get((n, spelt)) == w:
                        spans[d] += (s - int(words.first[d]), n)
                        items[d].update(owners[w])
            items = [sorted(x) for x in items]
            return summary(counts.tolist(), spans, items) if final else {"n_words": counts.tolist(), "spans": spans, "items": items}

        return each

    return append_struct(docs, into, RESULT if final else SCAN, text, work, keep, PART_BYTES)


def decontaminate(docs: DataFrame, benchmark: DataFrame, text: str = "text", item: str = "item_id", item_text: str = "text", into: str = "overlap", window: int = WINDOW, shingle: int = SHINGLE, block_bytes: int = BLOCK_BYTES, keep: list[str] | None = None) -> DataFrame:
    """All rows and columns of `docs` (or those in `keep`) with a struct `into`: words, words hit, items met and whether any word is hit.

    Nulls: a null text has no words; a null item text has no windows; a null item
    id counts as an item named by the empty string.  Items without words are
    ignored, an item shorter than a window is one window, repeated items and
    repeated documents are judged alike.  With no documents or no items the
    result is empty or clean.  `into` is lengthened if a column has that name.
    """
    into, keep = free_name(docs, into), docs.columns if keep is None else keep
    bench = benchmark.select(F.coalesce(quoted(item).cast("string"), F.lit("")).alias("i"), quoted(item_text).alias("t")).where("t is not null")
    size = bench.agg(F.coalesce(F.sum(F.octet_length("t")), F.lit(0))).first()[0]
    blocks = max(1, -(-size // block_bytes))
    spot = F.pmod(F.xxhash64("i", "t"), F.lit(blocks))

    def block_of(n: int) -> tuple[Block, dict]:
        block = Block([tuple(r) for r in bench.where(spot == n).collect()], window, shingle)  # about block_bytes
        return block, block.prefixes(_counted(docs, text, block.distinct())) if block.size else {}

    if blocks == 1:
        return _scan(docs, text, *block_of(0), into, keep, final=True)
    # the windows of all blocks meet per distinct text; rows with one text are judged alike
    mark = free_name(docs, "text_digest")
    digest = F.sha2(F.coalesce(quoted(text), F.lit("")), 256)
    keyed = docs.select(digest.alias(mark), quoted(text).alias(text))
    parts = None
    for n in range(blocks):
        # what a block finds is stored before the next one is gathered
        one = stored(_scan(keyed, text, *block_of(n), into, [mark]).where(F.size(f"{into}.items") > 0).dropDuplicates([mark]), "overlap-block")
        parts = one if parts is None else parts.union(one)
    names = {c: free_name(docs, f"met_{c}") for c in ("spans", "items")}
    lists = [F.flatten(F.collect_list(f"{into}.{c}")).alias(n) for c, n in names.items()]  # one from each block at most
    met = stored(parts.groupBy(mark).agg(*lists), "overlaps")
    base = _scan(docs.withColumn(mark, digest), text, Block([], window, shingle), {}, into, [*keep, mark])
    found = base.join(met, mark, "left").select(*keep, F.struct(F.col(f"{into}.n_words").alias("n_words"), *(F.coalesce(n, f"{into}.{c}").alias(c) for c, n in names.items())).alias(into))
    schema = T.StructType([*(f for f in docs.schema.fields if f.name in keep), T.StructField(into, RESULT, False)])

    def finish(batches):
        kinds = {f.name: to_arrow_type(f.dataType) for f in RESULT}
        for batch in batches:
            s = batch.column(batch.schema.get_field_index(into))
            n, spans, items = (s.field(c).to_pylist() for c in ("n_words", "spans", "items"))
            got = summary(n, spans, [sorted(set(x)) for x in items])
            made = pa.StructArray.from_arrays([pa.array(got[c], kinds[c]) for c in kinds], list(kinds))
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(c)) for c in keep), made], names=[*keep, into])

    return found.mapInArrow(finish, schema)
