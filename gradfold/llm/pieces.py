"""SentencePiece encoding and decoding that keeps byte offsets.

The text is normalised by the model's compiled character map: a double-array
trie, walked from each place to the longest prefix it holds, whose replacement
records the source bytes it came from.  Pieces of the normalised text project
through those records to spans of the original bytes.

Byte-pair merging never joins two characters that stand together in no piece of
the vocabulary, so the text is cut at such places (before each run of spaces, around
line feeds), and the segmentations of short cuts, mostly words, are remembered.
The map is walked only from places whose byte begins an entry of it; between them
a text is its own normal form.  Tests compare ids and decoded texts with the
library.
"""

from __future__ import annotations

import hashlib
import heapq
import re
import struct
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .shared import append_struct

SPACE = "▁"
#: How many segmentations a worker remembers, of cuts of at most so many characters.
REMEMBERED, SHORT = 1 << 18, 48
_CUTS = re.compile(f"\n|{SPACE}+[^{SPACE}\n]*|[^{SPACE}\n]+")
#: Piece types of the public model format.
NORMAL, UNKNOWN, CONTROL, USER_DEFINED, UNUSED, BYTE = 1, 2, 3, 4, 5, 6


def _fields(raw: bytes):
    """(number, value) of each field of a protocol buffer message; nested messages are bytes."""
    at, n = 0, len(raw)

    def varint():
        nonlocal at
        out = shift = 0
        while True:
            b = raw[at]
            at += 1
            out |= (b & 127) << shift
            if b < 128:
                return out
            shift += 7

    while at < n:
        key = varint()
        kind = key & 7
        if kind == 0:
            yield key >> 3, varint()
        elif kind == 2:
            size = varint()
            yield key >> 3, raw[at : at + size]
            at += size
        else:
            size = 8 if kind == 1 else 4
            yield key >> 3, raw[at : at + size]
            at += size


class CharacterMap:
    """A compiled character map: a double-array trie from UTF-8 prefixes to replacements."""

    def __init__(self, blob: bytes):
        size = struct.unpack_from("<I", blob)[0] if blob else 0
        self.units = np.frombuffer(blob, "<u4", size // 4, 4).tolist() if size else []
        self.texts = blob[4 + size :] if blob else b""
        first = bytes(b for b in range(256) if self._begins(b))
        #: Finds the bytes that begin an entry.
        self.starts = re.compile(b"[" + re.escape(first) + b"]") if first else None

    def _begins(self, byte: int) -> bool:
        if not self.units:
            return False
        root = self.units[0]
        at = (root >> 10 << ((root & 512) >> 6)) ^ byte
        return at < len(self.units) and self.units[at] & 0x800000FF == byte

    def longest(self, raw: bytes, at: int) -> tuple[int, bytes] | None:
        """(bytes used, replacement) of the longest prefix of raw[at:] that the map has."""
        if not self.units:
            return None
        units, found = self.units, None
        node = 0
        unit = units[0]
        node ^= unit >> 10 << ((unit & 512) >> 6)
        for i in range(at, len(raw)):
            node ^= raw[i]
            unit = units[node]
            if unit & 0x800000FF != raw[i]:
                break
            node ^= unit >> 10 << ((unit & 512) >> 6)
            if unit >> 8 & 1:
                found = (i + 1 - at, units[node] & 0x7FFFFFFF)
        if not found:
            return None
        end = self.texts.index(b"\0", found[1])
        return found[0], self.texts[found[1] : end]


class Codec:
    """Encoder and decoder of a byte-pair model of the public piece format."""

    def __init__(self, blob: bytes):
        self.pieces, self.scores, self.kinds = [], [], []
        self.byte_fallback, trainer, chars = False, {}, b""
        self.dummy = self.squeeze = self.escape = True
        for number, value in _fields(blob):
            if number == 1:
                one = dict(_fields(value))
                self.pieces.append(one.get(1, b"").decode())
                self.scores.append(struct.unpack("<f", one[2])[0] if 2 in one else 0.0)
                self.kinds.append(one.get(3, NORMAL))
            elif number == 2:
                trainer = dict(_fields(value))
            elif number == 3:
                norm = dict(_fields(value))
                chars = norm.get(2, b"")
                self.dummy, self.squeeze, self.escape = (bool(norm.get(k, 1)) for k in (3, 4, 5))
        if trainer.get(3, 1) != 2 or trainer.get(24, 0) or UNUSED in self.kinds or USER_DEFINED in self.kinds or not self.escape:
            raise ValueError("only byte-pair models with spaces as prefixes and without unused or user-defined pieces are supported")
        self.map = CharacterMap(chars)
        self.ids = {p: i for i, (p, k) in enumerate(zip(self.pieces, self.kinds, strict=True)) if k == NORMAL}
        self.byte_ids = {int(p[3:5], 16): i for i, (p, k) in enumerate(zip(self.pieces, self.kinds, strict=True)) if k == BYTE}
        self.unknown, self.begin, self.end = self.kinds.index(UNKNOWN), self.pieces.index("<s>"), self.pieces.index("</s>")
        joined = [p for p in self.ids if len(p) > 1]
        #: May a text be cut before each run of spaces, and around line feeds?
        self.cuts = not any(b == SPACE != a for p in joined for a, b in zip(p, p[1:], strict=False)) and not any("\n" in p for p in joined)
        self.native = sentencepiece.SentencePieceProcessor(model_proto=blob)
        self.bytes_of = [bytes([int(p[3:5], 16)]) if k == BYTE else b"" if k == CONTROL else p.replace(SPACE, " ").encode() for p, k in zip(self.pieces, self.kinds, strict=True)]
        #: Bytes of each piece in a normalised text.
        self.sizes = np.array([1 if k == BYTE else 0 if k == CONTROL else len(p.encode()) for p, k in zip(self.pieces, self.kinds, strict=True)], "<u4")
        self.lengths = np.array([len(b) for b in self.bytes_of], np.int64)
        self.verbatim = self.map.starts is None and self.dummy and not self.squeeze and bool(self.byte_ids)
        self._known: dict[str, tuple[bytes, bytes, bytes]] = {}

    # normalisation

    def normalise(self, text: str) -> tuple[str, np.ndarray]:
        """The normalised text, and for each of its UTF-8 bytes (and its end) the source byte that it comes from."""
        raw = text.encode()
        if self.squeeze or not raw or self.map.starts and self.map.starts.search(raw):
            chars, source = self._walked(raw)
            return chars, np.array(source, np.int64)
        # no entry of the map begins in this text: only spaces change, into marks of three bytes
        times = np.where(np.frombuffer(raw, np.uint8) == 0x20, len(SPACE.encode()), 1)
        source = np.append(np.repeat(np.arange(len(raw)), times), len(raw))
        chars = text.replace(" ", SPACE)
        return (SPACE + chars, np.append(np.zeros(len(SPACE.encode()), np.int64), source)) if self.dummy else (chars, source)

    def _walked(self, raw: bytes) -> tuple[str, list[int]]:
        """The same place by place, each by the longest prefix that the map has."""
        out, source, at = bytearray(), [], 0
        mark = SPACE.encode()

        def step(at: int) -> tuple[int, bytes]:
            found = self.map.longest(raw, at)
            if found:
                return found
            size = 1 if raw[at] < 0x80 else 2 if raw[at] < 0xE0 else 3 if raw[at] < 0xF0 else 4
            return size, raw[at : at + size]

        if self.squeeze:
            while at < len(raw):
                size, new = step(at)
                if new != b" ":
                    break
                at += size
        if at == len(raw):
            return "", [len(raw)]

        def put(piece: bytes, frm: int):
            out.extend(piece)
            source.extend([frm] * len(piece))

        if self.dummy:
            put(mark, at)
        blank = self.squeeze
        while at < len(raw):
            size, new = step(at)
            while blank and new.startswith(b" "):
                new = new[1:]
            if new:
                put(new.replace(b" ", mark), at)
                blank = self.squeeze and new.endswith(b" ")
            at += size
            if not self.squeeze:
                blank = False
        if self.squeeze:
            while out.endswith(mark):
                cut = len(out) - len(mark)
                at = source[cut]
                del out[cut:], source[cut:]
        source.append(at)
        return out.decode(), source

    # segmentation

    def merge(self, chars: str) -> list[str]:
        """Byte-pair merging of a normalised text: the best-scored pair first, of ties the leftmost."""
        ids, scores = self.ids, self.scores
        parts: list[str | None] = list(chars)
        left, right = list(range(-1, len(parts) - 1)), [*range(1, len(parts)), -1]
        queue: list[tuple[float, int, int, int]] = []

        def offer(a: int, b: int):
            if a >= 0 and b >= 0 and (found := ids.get(parts[a] + parts[b])) is not None:
                heapq.heappush(queue, (-scores[found], a, b, len(parts[a]) + len(parts[b])))

        for i in range(1, len(parts)):
            offer(i - 1, i)
        while queue:
            _, a, b, size = heapq.heappop(queue)
            if parts[a] is None or parts[b] is None or len(parts[a]) + len(parts[b]) != size or right[a] != b:
                continue
            parts[a] += parts[b]
            parts[b] = None
            right[a] = right[b]
            if right[b] >= 0:
                left[right[b]] = a
            offer(left[a], a)
            offer(a, right[a])
        return [p for p in parts if p is not None]

    def segment(self, chars: str) -> list[tuple[int, int]]:
        """(id, bytes of the normalised text) of each piece."""
        out: list[tuple[int, int]] = []
        for p in self.merge(chars):
            found = self.ids.get(p)
            raw = p.encode()
            if found is not None:
                out.append((found, len(raw)))
            elif self.byte_ids:
                out += [(self.byte_ids[b], 1) for b in raw]
            elif out and out[-1][0] == self.unknown:
                out[-1] = (self.unknown, out[-1][1] + len(raw))
            else:
                out.append((self.unknown, len(raw)))
        return out

    def _cut(self, chars: str) -> list[str]:
        return _CUTS.findall(chars) if self.cuts else [chars] if chars else []

    def _segmented(self, cuts: set[str]) -> None:
        """Remember ids and normalised bytes of the pieces of cuts, as little-endian unsigned 32-bit integers, and the bytes that they decode to."""
        # a word after one mark, of a model that leaves texts as they are, is what the library's merging gets for the word alone
        words = [c for c in cuts if c[0] == SPACE and c.find(SPACE, 1) < 0] if self.verbatim else []
        if words:
            own = self.native.encode([c[1:] for c in words], num_threads=1)
            flat = np.fromiter(chain.from_iterable(own), np.int64)
            at = np.concatenate([[0], np.cumsum(np.fromiter(map(len, own), np.int64, len(own)))])
            ids, sizes, texts = flat.astype("<u4").tobytes(), self.sizes[flat].tobytes(), b"".join(map(self.bytes_of.__getitem__, flat.tolist()))
            to = np.concatenate([[0], np.cumsum(self.lengths[flat])])[at].tolist()
            at = (4 * at).tolist()
            for n, cut in enumerate(words):
                if at[n] < at[n + 1]:
                    self._known[cut] = ids[at[n] : at[n + 1]], sizes[at[n] : at[n + 1]], texts[to[n] : to[n + 1]]
        for cut in cuts:
            if cut not in self._known:
                pieces = self.segment(cut)
                self._known[cut] = np.array([i for i, _ in pieces], "<u4").tobytes(), np.array([n for _, n in pieces], "<u4").tobytes(), b"".join([self.bytes_of[i] for i, _ in pieces])

    def coded_many(self, texts: list[str]) -> list[tuple[np.ndarray, np.ndarray, np.ndarray, bytes]]:
        """For each text all ids, the first source byte of each and one past its last, and the decoded text in UTF-8.

        The begin id spans (0, 0) and the end id the text's end.
        """
        normal = [self.normalise(t) for t in texts]
        cuts = [self._cut(chars) for chars, _ in normal]
        every = set().union(*cuts)
        need = every - self._known.keys()
        if len(self._known) + len(need) > REMEMBERED:
            self._known.clear()
            need = every
        self._segmented(need)
        out = [self._joined(t, source, [self._known[c] for c in own]) for t, (_, source), own in zip(texts, normal, cuts, strict=True)]
        for c in need:
            if len(c) > SHORT:
                del self._known[c]
        return out

    def _joined(self, text: str, source: np.ndarray, parts: list[tuple[bytes, bytes, bytes]]) -> tuple[np.ndarray, np.ndarray, np.ndarray, bytes]:
        own = np.frombuffer(b"".join([p[0] for p in parts]), "<u4")
        sizes = np.frombuffer(b"".join([p[1] for p in parts]), "<u4").astype(np.int64)
        ends, size = np.cumsum(sizes), len(text.encode())
        ids = np.concatenate([[self.begin], own, [self.end]]).astype("<u4")
        starts = np.concatenate([[0], source[ends - sizes], [size]]).astype("<u4")
        stops = np.concatenate([[0], source[ends], [size]]).astype("<u4")
        if self.byte_ids:
            raw = b"".join([p[2] for p in parts])
            return ids, starts, stops, raw[1:] if raw.startswith(b" ") and (self.dummy or self.squeeze) else raw
        return ids, starts, stops, self.decode(ids.tolist()).encode()

    def coded(self, text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, bytes]:
        return self.coded_many([text])[0]

    def spans(self, text: str) -> list[tuple[int, int, int]]:
        """(id, first byte, one past the last byte of the original text) of each piece; no begin and end ids."""
        ids, starts, ends, _ = self.coded(text)
        return list(zip(ids.tolist(), starts.tolist(), ends.tolist(), strict=True))[1:-1]

    # decoding

    def _plain_decode(self, ids: list[int]) -> str:
        out, run = [], bytearray()

        def flush():
            if run:
                out.append(_replaced(bytes(run)))
                run.clear()

        for i in ids:
            kind = self.kinds[i]
            if kind == BYTE:
                run.append(int(self.pieces[i][3:5], 16))
                continue
            flush()
            if kind == UNKNOWN:
                out.append(" ⁇ ")
            elif kind != CONTROL:
                out.append(self.pieces[i].replace(SPACE, " "))
        flush()
        return "".join(out)

    def decode(self, ids: list[int]) -> str:
        """The text of a list of ids; the first space is the dummy one, control ids are silent."""
        text = self._plain_decode(ids)
        first = next((i for i in ids if self.kinds[i] != CONTROL), None)
        starts = first is not None and self.pieces[first].startswith(SPACE)
        return text[1:] if starts and (self.dummy or self.squeeze) else text


def _replaced(raw: bytes) -> str:
    """Decode UTF-8; each byte that is not part of a character becomes U+FFFD."""
    try:
        return raw.decode()
    except UnicodeDecodeError:
        out, at = [], 0
        while at < len(raw):
            for size in (1, 2, 3, 4):
                try:
                    out.append(raw[at : at + size].decode())
                    at += size
                    break
                except UnicodeDecodeError:
                    continue
            else:
                out.append("�")
                at += 1
        return "".join(out)


@lru_cache(2)
def codec(blob: bytes) -> Codec:
    return Codec(blob)


def load(path: str) -> bytes:
    """A model file, read by the driver; its bytes go to the executors (half a megabyte here)."""
    with open(path, "rb") as f:
        blob = f.read()
    if len(blob) > 64 << 20:
        raise ValueError("a piece model of over 64 MB is not broadcast")
    return blob


CODED = T.StructType([T.StructField("n_tokens", T.LongType(), False), T.StructField("ids_sha256", T.StringType(), False), T.StructField("decoded_sha256", T.StringType(), False), T.StructField("spans_sha256", T.StringType(), False)])
FULL = T.StructType([T.StructField(n, T.ArrayType(T.IntegerType(), False), False) for n in ("ids", "starts", "ends")] + [T.StructField("decoded", T.StringType(), False)])


def _each_text(part: pa.RecordBatch, text: str):
    return (t or "" for t in part.column(part.schema.get_field_index(text)).to_pylist())


def encode(docs: DataFrame, model: bytes, text: str = "text", into: str = "coded", keep: list[str] | None = None) -> DataFrame:
    """All rows and columns with a struct of `ids` (begin and end ids included), byte spans `starts` and `ends` in the original text, and the `decoded` text.

    The begin id spans (0, 0) and the end id the text's end.  Null is encoded as an empty text.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def work():
        c = codec(shared.value)

        def each(part):
            out = {n: [] for n in ("ids", "starts", "ends", "decoded")}
            for ids, starts, ends, decoded in c.coded_many(list(_each_text(part, text))):
                out["ids"].append(ids.astype(np.int32))
                out["starts"].append(starts.astype(np.int32))
                out["ends"].append(ends.astype(np.int32))
                out["decoded"].append(decoded.decode())
            return out

        return each

    return append_struct(docs, into, FULL, text, work, keep)


def digests(docs: DataFrame, model: bytes, text: str = "text", into: str = "coded", keep: list[str] | None = None) -> DataFrame:
    """All rows and columns with a struct of the number of ids and the SHA-256 of ids, of the decoded text and of the byte spans.

    Null is encoded as an empty text, which has the begin and end ids only; repeated rows come out alike.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def work():
        c = codec(shared.value)
        sha = hashlib.sha256

        def each(part):
            out = {"n_tokens": [], "ids_sha256": [], "decoded_sha256": [], "spans_sha256": []}
            for ids, starts, ends, decoded in c.coded_many(list(_each_text(part, text))):
                out["n_tokens"].append(len(ids))
                out["ids_sha256"].append(sha(ids.tobytes()).hexdigest())
                out["decoded_sha256"].append(sha(decoded).hexdigest())
                out["spans_sha256"].append(sha(np.stack([starts, ends], axis=1).tobytes()).hexdigest())
            return out

        return each

    return append_struct(docs, into, CODED, text, work, keep)
