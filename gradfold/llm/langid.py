"""Language identification by segmentation-marginalised unigrams.

A language is a distribution over the pieces of a fixed public vocabulary.  The
probability of a word is the sum over all its segmentations into pieces, from a
forward recursion over the word's characters, and that of a text is the product
over its words.  Pieces do not cross words, so each distinct word of a slice of
texts is scored once, for all languages and many words at a time.

The distributions are learnt from a bounded sample of labelled texts, as smoothed counts
of the pieces of the vocabulary's own segmentation.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels
from .pieces import SPACE, codec
from .shared import append_struct, quoted

#: Labelled texts of each language that the distributions are learnt from, about; chosen by a hash of the id.
SAMPLE = 1500
#: Added to each piece's count, and the probability of a character that no piece covers.
SMOOTH, UNKNOWN = 0.05, 1e-7
#: Distinct words that a Python worker remembers: the first it meets, among them those that are frequent.
REMEMBERED = 300_000


@dataclass
class Model:
    languages: list[str]
    prior: np.ndarray
    #: piece -> row of `probs`
    rows: dict[str, int]
    #: (pieces + 1, languages); the last row is for characters without a piece
    probs: np.ndarray


def _flat(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of words end to end, and where each ends."""
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)))
    return np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64), ends


def _finish(h: np.ndarray, size: int) -> np.ndarray:
    return kernels.mixed(h + np.uint64(size * kernels._STEP & (1 << 64) - 1))


def _prefixes(chars: np.ndarray, starts: np.ndarray, size: int) -> np.ndarray:
    return _finish(kernels.rolling(chars, starts, starts + size, kernels._BASE), size)


class Scorer:
    """Log probabilities of words under all languages of a model."""

    def __init__(self, model: Model):
        self.model, self.n = model, len(model.languages)
        self.last = len(model.probs) - 1
        #: Characters of the longest piece: no segmentation has a longer step.
        self.longest = max(map(len, model.rows), default=1)
        chars, ends = _flat(list(model.rows))
        starts = np.concatenate([[0], ends[:-1]])
        row_of = np.fromiter(model.rows.values(), np.int64, len(model.rows))
        hashes, rows = [], []
        for k in range(1, self.longest + 1):
            has = starts + k <= ends
            hashes.append(_prefixes(chars, starts[has], k))
            rows.append(np.where(starts[has] + k == ends[has], row_of[has], -1))
        hashes, rows = np.concatenate(hashes), np.concatenate(rows)
        order = np.lexsort((-rows, hashes))
        members, first = np.unique(hashes[order], return_index=True)
        #: Every prefix of a piece, and the row of the piece if it is a whole one.
        self.probe, self.row_of = kernels.Probe(members, 20), rows[order][first]
        self.known: dict[str, int] = {}
        self.scores = np.zeros((1 << 12, self.n))

    def edges(self, chars: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(begin, length, row) of every piece in words laid end to end; each character has one of length one at least."""
        sizes = np.diff(ends, prepend=0)
        limit = np.repeat(ends, sizes)
        up, down = kernels.powers(kernels._BASE, len(chars) + 1)
        total = np.zeros(len(chars) + 1, np.uint64)
        np.cumsum(chars * up[:-1], out=total[1:])
        alive = np.arange(len(chars))
        out = []
        for k in range(1, self.longest + 1):
            alive = alive[alive + k <= limit[alive]]
            at, which = self.probe.find(_finish((total[alive + k] - total[alive]) * down[alive], k))
            rows = self.row_of[which]
            if k == 1:
                first = np.full(len(alive), self.last)
                first[at] = np.where(rows >= 0, rows, self.last)
                out.append((alive, np.ones(len(alive), np.int64), first))
            else:
                whole = rows >= 0
                out.append((alive[at[whole]], np.full(whole.sum(), k), rows[whole]))
            alive = alive[at]
            if not len(alive):
                break
        return tuple(np.concatenate(c) for c in zip(*out, strict=True))

    def many(self, words: list[str]) -> np.ndarray:
        """(words, languages): the forward recursion of all words side by side, one character at a time."""
        chars, ends = _flat([SPACE + w for w in words])
        sizes = np.diff(ends, prepend=0)
        begin, length, row = self.edges(chars, ends)
        owner = np.repeat(np.arange(len(words)), sizes)[begin]
        begin = begin - (ends - sizes)[owner]
        order = np.argsort(begin + length, kind="stable")
        begin, length, row, owner = begin[order], length[order], row[order], owner[order]
        finish = begin + length
        top = int(sizes.max(initial=0))
        # a ring of the last self.longest + 1 places, each word scaled by what `scale` remembers
        ring = np.zeros((self.longest + 1, len(words), self.n))
        ring[0] = 1
        scale = np.zeros((len(words), self.n))
        out = np.zeros((len(words), self.n))
        cuts = np.searchsorted(finish, np.arange(1, top + 2))
        for at in range(1, top + 1):
            here = slice(cuts[at - 1], cuts[at])
            who = owner[here]
            ring[at % (self.longest + 1)] = 0
            add = ring[begin[here] % (self.longest + 1), who] * self.model.probs[row[here]]
            now = ring[at % (self.longest + 1)]
            for j in range(self.n):
                now[:, j] = np.bincount(who, add[:, j], len(words))
            done = sizes == at
            if done.any():
                out[done] = np.log(np.maximum(now[done], 1e-300)) + scale[done]
            if at % 12 == 0:
                live = np.flatnonzero(sizes > at)
                if not len(live):
                    break
                peak = np.maximum(now[live], 1e-300)
                ring[:, live] /= peak
                scale[live] += np.log(peak)
        return out

    def texts(self, texts: list[str]) -> np.ndarray:
        """(texts, languages): log probabilities without the prior."""
        split = [t.split() for t in texts]
        known = self.known
        missing = list(set().union(*split).difference(known))
        first = len(known)
        if len(self.scores) < first + len(missing):
            self.scores = np.resize(self.scores, (2 * (first + len(missing)), self.n))
        known.update(zip(missing, range(first, first + len(missing)), strict=True))
        by_size = sorted(missing, key=len)
        for i in range(0, len(by_size), 4096):
            some = by_size[i : i + 4096]
            self.scores[[known[w] for w in some]] = self.many(some)
        out = np.zeros((len(texts), self.n))
        for i, words in enumerate(split):
            if words:
                out[i] = self.scores[np.fromiter(map(known.__getitem__, words), np.int64, len(words))].sum(axis=0)
        if len(known) > REMEMBERED:
            for w in missing:
                del known[w]
        return out


def _sampled(docs: DataFrame, ident: str, text: str, lang: str, learn, per_language: int) -> DataFrame:
    labelled = docs.where(learn).where(quoted(lang).isNotNull() & quoted(text).isNotNull())
    counts = {r[0]: r[1] for r in labelled.groupBy(quoted(lang)).count().collect()}  # one row for each language
    spot = (F.xxhash64(quoted(ident).cast("string"), F.lit("language sample")).bitwiseAND(F.lit((1 << 40) - 1).cast("long")) / float(1 << 40)).cast("double")
    share = F.coalesce(*(F.when(quoted(lang) == n, F.lit(min(1.0, per_language / c))) for n, c in counts.items()), F.lit(0.0)) if counts else F.lit(0.0)
    return labelled.where(spot < share).select(quoted(lang).alias("lang"), quoted(text).alias("text")), counts


def train(docs: DataFrame, vocabulary: bytes, ident: str = "doc_id", text: str = "text", lang: str = "lang", learn=None, per_language: int = SAMPLE) -> Model:
    """Learn from about `per_language` texts of each language among the rows where `learn` holds.

    Piece counts are summed on the executors; the driver gets at most one number
    for each language and piece.  Rows with a null language or text are no examples.
    """
    spark = docs.sparkSession
    sample, counts = _sampled(docs, ident, text, lang, F.lit(True) if learn is None else learn, per_language)
    languages = sorted(counts)
    shared = spark.sparkContext.broadcast(vocabulary)

    def count(batches):
        c = codec(shared.value)
        total: dict[str, np.ndarray] = {}
        for batch in batches:
            for name, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids = np.array(c.native.encode(" ".join(t.split())), np.int64)
                if name not in total:
                    total[name] = np.zeros(len(c.pieces), np.int64)
                total[name] += np.bincount(ids, minlength=len(c.pieces))
        for name, n in total.items():
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(at), pa.string()), pa.array(at.astype(np.int32)), pa.array(n[at])], names=["lang", "piece", "n"])

    got = sample.mapInArrow(count, "lang string, piece int, n long").groupBy("lang", "piece").agg(F.sum("n").alias("n")).collect()
    c = codec(vocabulary)
    usable = {i: r for r, i in enumerate(sorted(c.ids.values()))}
    weights = np.full((len(usable) + 1, max(1, len(languages))), SMOOTH)
    place = {n: j for j, n in enumerate(languages)}
    for name, piece, n in got:
        if piece in usable:
            weights[usable[piece], place[name]] += n
    weights[-1] = 0
    probs = weights / weights.sum(axis=0, keepdims=True)
    probs[-1] = UNKNOWN
    total = sum(counts.values())
    prior = np.log(np.array([(counts[n] + 1) / (total + len(languages)) for n in languages]) if languages else np.ones(1))
    return Model(languages, prior, {c.pieces[i]: r for i, r in usable.items()}, probs)


PREDICTED = T.StructType([T.StructField("lang_pred", T.StringType(), False), T.StructField("score", T.DoubleType(), False)])


def predict(docs: DataFrame, model: Model, text: str = "text", into: str = "language", keep: list[str] | None = None) -> DataFrame:
    """All rows and columns with a struct of the likeliest language and its posterior probability.

    A null text, or one without a letter, is `und` with score 0, as is every text if no language was learnt.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def work():
        m = shared.value
        scorer = Scorer(m)

        def each(part):
            texts = [t or "" for t in part.column(part.schema.get_field_index(text)).to_pylist()]
            named = [bool(m.languages) and any(map(str.isalpha, t)) for t in texts]
            if not m.languages:
                return {"lang_pred": ["und"] * len(texts), "score": [0.0] * len(texts)}
            logs = scorer.texts(texts) + m.prior
            best = logs.argmax(axis=1)
            post = 1 / np.exp(logs - logs.max(axis=1, keepdims=True)).sum(axis=1)
            return {"lang_pred": [m.languages[b] if ok else "und" for b, ok in zip(best.tolist(), named, strict=True)], "score": [p if ok else 0.0 for p, ok in zip(post.tolist(), named, strict=True)]}

        return each

    return append_struct(docs, into, PREDICTED, text, work, keep)
