"""The corpus operators against brute force on small tables, and on the cases that go wrong first."""

import hashlib
import itertools
import random
import re
import zlib
from collections import defaultdict
from fractions import Fraction

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from gradfold.llm import components, decontaminate, exact, kernels, langid, lines, pieces, quality, sharding, similar, simhash, substring, urlfilter
from gradfold.llm.queries import piece_model, queries, table

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs_frame(spark, rows):
    return spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], DOCS)


ODD = [(1, None), (2, ""), (3, "   \n\t "), (4, "one"), (5, "one"), (6, "Ünïcode ñ 中文 🙂 Straße"), (7, "a b c d e f g h i j k l m"), (7, "a b c d e f g h i j k l m"), (None, "a b c"), (8, "word " * 5000), (9, "x" * 200_000), (10, "a\x00b c\rd\x0be\x0cf"), (11, "A B C D E F G H I J K L M")]


@pytest.fixture(scope="module")
def odd(spark):
    # extra columns whose names clash with what operators add
    names = ["overlap", "coded", "quality", "language", "simhash", "rank", "text_digest", "part", "at", "shard", "w", "winner", "items", "spans", "n_keep", "digest"]
    return docs_frame(spark, ODD).withColumns({n: F.lit("mine") for n in names})


@pytest.fixture(scope="module")
def empty(spark):
    return docs_frame(spark, [(1, "a")]).where("false")


def mutated(rng, words, n):
    words = list(words)
    for _ in range(n):
        words[rng.randrange(len(words))] = f"w{rng.randrange(10**6)}"
    return words


@pytest.fixture(scope="module")
def corpus(spark, sf):
    """The documents of the smallest scale, with planted copies, near copies and shared passages."""
    rng = random.Random(3)
    rows = [(r.doc_id, r.text) for r in table(spark, sf, "documents").select("doc_id", "text").collect()]
    base = [t for _, t in rows if len(t.split()) > 80][:12]
    shared = base[0].split()[:70]
    extra = []
    for i, t in enumerate(base):
        w = t.split()
        extra.append((10_000 + i, t))
        extra.append((10_100 + i, " ".join(mutated(rng, w, 1))))
        extra.append((10_200 + i, " ".join(w[:20] + shared + w[20:])))
        extra.append((10_300 + i, "\n".join(t.split("\n") + [base[1].split("\n")[0] + "!"])))
    return docs_frame(spark, rows + extra + [(20_000, None), (20_001, ""), (20_002, " ")]).persist()


def collected(df):
    return [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]


# kernels


def test_words_and_hashes():
    texts = ["Ab1 c-d", "", "é x", "  ", "z"]
    import pyarrow as pa

    w = kernels.alnum_words(*kernels.text_bytes(pa.array([None, *texts])))
    assert w.counts.tolist() == [0, 3, 0, 2, 0, 1]
    assert [w.data[a:b].tobytes().decode() for a, b in zip(w.starts, w.ends)] == ["ab1", "c", "d", "é", "x", "z"]
    one, two = (kernels.spaced_words(*kernels.text_bytes(pa.array([t]))).hashes().tolist() for t in ("q a b c", "a b c a"))
    assert one[1:] == two[:3] and two[0] == two[3]


def test_minimizers_depend_on_the_window_only():
    rng = np.random.default_rng(0)
    h = rng.integers(0, 1 << 63, 300).astype(np.uint64)
    at = kernels.minimizers(h, 5, 20)
    again = kernels.minimizers(np.concatenate([h[100:150], h[:40]]), 5, 20)
    assert (again[:30] + 100 == at[100:130]).all()
    assert ((at >= np.arange(len(at))) & (at + 5 <= np.arange(len(at)) + 20)).all()


def test_components_against_union_find(spark):
    rng = random.Random(1)
    pairs = [(rng.randrange(60), rng.randrange(60)) for _ in range(40)] + [(i, i + 1) for i in range(100, 140)] + [(200, i) for i in range(201, 260)]
    root = {}

    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        if a != b:
            a, b = find(a), find(b)
            root[max(a, b)] = min(a, b)
    got = {r.node: r.component for r in components.components(spark.createDataFrame(pairs, "a long, b long")).collect()}
    assert got == {x: find(x) for x in root}


# 1


def brute_overlap(docs, items, window=10):
    split = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    wins = defaultdict(set)
    for name, t in items:
        w = split(t)
        n = min(window, len(w))
        for i in range(len(w) - n + 1) if w else ():
            wins[tuple(w[i : i + n])].add(name)
    sizes = {len(w) for w in wins}
    out = []
    for i, t in docs:
        w, hit, met = split(t), set(), set()
        for n in sizes:
            for s in range(len(w) - n + 1):
                if names := wins.get(tuple(w[s : s + n])):
                    hit.update(range(s, s + n))
                    met |= names
        ids = sorted(str(x) for x in met)
        out.append((i, len(w), len(hit), len(ids), hashlib.sha256(",".join(ids).encode()).hexdigest(), bool(hit)))
    return out


def flat(df):
    return [tuple(r) for r in df.select("doc_id", *(f"overlap.{c}" for c in ("n_words", "n_hit", "n_items", "items_sha256", "contaminated"))).collect()]


@pytest.mark.parametrize("block", [4 << 20, 2500])
def test_decontamination(spark, sf, corpus, block):
    items = [(r.item_id, r.text) for r in table(spark, sf, "benchmark").collect()] + [(900, "One"), (901, "b C"), (902, "c d e f g h i j k l m"), (903, ""), (904, None)]
    bench = spark.createDataFrame(items, "item_id long, text string")
    docs = docs_frame(spark, [r for r in collected(corpus) if r[0] is not None] + [x for x in ODD if x[0] is not None])
    got = flat(decontaminate.decontaminate(docs, bench, block_bytes=block, keep=["doc_id"]))
    assert sorted(got) == sorted(brute_overlap(collected(docs), items))
    assert any(g[5] for g in got)


# 2


def brute_simhash(docs, most=2):
    out = []
    for i, t in docs:
        w = re.sub("[A-Z]", lambda m: m[0].lower(), t or "")
        w = re.findall(r"[^\x20\x09-\x0D]+", w)
        sh = [" ".join(w[k : k + 3]) for k in range(max(1, len(w) - 2))] if w else []
        hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
        out.append((i, sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs)) if hs else 0))
    n = len(out)
    root = list(range(n))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for a, b in itertools.combinations(range(n), 2):
        if bin(out[a][1] ^ out[b][1]).count("1") <= most:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    least = {}
    for k, (i, _) in enumerate(out):
        if i is not None:
            r = find(k)
            least[r] = min(i, least.get(r, i))
    return [(i, f"{f:016x}", least.get(find(k))) for k, (i, f) in enumerate(out)]


def ordered(rows):
    return sorted(rows, key=str)


def test_simhash(spark, corpus, odd):
    docs = corpus.unionByName(odd.select(*corpus.columns))
    got = [tuple(r) for r in simhash.near_duplicates(docs).collect()]
    want = brute_simhash(collected(docs))
    assert ordered(got) == ordered(want)
    assert len({g[2] for g in got}) < len(got) - 10


@pytest.mark.parametrize("dense", [2048, 2])
def test_links_of_crowded_fingerprints(spark, dense):
    rng = random.Random(5)
    center = rng.getrandbits(64)
    prints = {center}
    for _ in range(150):
        p = center
        for b in rng.sample(range(64), rng.randrange(0, 5)):
            p ^= 1 << b
        prints.add(p)
    prints |= {rng.getrandbits(64) for _ in range(100)}
    signed = [p - (1 << 64) if p >> 63 else p for p in prints]
    frame = spark.createDataFrame([(i, p) for i, p in enumerate(signed)], "i long, bits long")
    got = {r.bits: r.component_id for r in simhash.classes(frame, "i", dense=dense).collect()}
    root = list(range(len(signed)))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for a, b in itertools.combinations(range(len(signed)), 2):
        if bin((signed[a] ^ signed[b]) & (1 << 64) - 1).count("1") <= 2:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    assert got == {p: find(i) for i, p in enumerate(signed)}


@pytest.mark.parametrize("dense", [2048, 1])
def test_simhash_broadcasts_nothing(spark, corpus, monkeypatch, dense):
    plans, write = [], simhash.stored

    def noted(df, label):
        plans.append(df._jdf.queryExecution().executedPlan().toString())
        return write(df, label)

    for module in (simhash, components):
        monkeypatch.setattr(module, "stored", noted)
    out = simhash.near_duplicates(corpus, dense=dense)
    plans.append(out._jdf.queryExecution().executedPlan().toString())
    assert sum("SortMergeJoin" in p for p in plans) >= 4 and not any("Broadcast" in p for p in plans)


def test_simhash_keeps_one_of_each(spark, corpus, odd):
    docs = corpus.unionByName(odd.select(*corpus.columns).withColumn("doc_id", F.col("doc_id") + 50_000))  # ids of two classes must differ
    want = {c for _, _, c in brute_simhash(collected(docs))}
    kept = simhash.one_of_each(docs)
    assert kept.columns == docs.columns
    assert ordered(r.doc_id for r in kept.collect()) == ordered(want)  # a class of rows without ids keeps one, too


# 3


def test_exact(spark, corpus, odd):
    docs = corpus.unionByName(odd.select(*corpus.columns))
    rows = collected(docs)
    groups = defaultdict(list)
    for i, t in rows:
        groups[t or ""].append(i)
    top = {t: max((i for i in g if i is not None), default=None) for t, g in groups.items()}
    want = [(i, top[t or ""], len(groups[t or ""]), i == top[t or ""], hashlib.sha256((t or "").encode()).hexdigest()) for i, t in rows]
    got = [tuple(r) for r in exact.deduplicate(docs, exact.DigestIndex.create(spark)).collect()]
    assert ordered(got) == ordered(want)
    kept = exact.unique_rows(docs, exact.DigestIndex.create(spark))
    assert kept.columns == docs.columns
    assert sorted((r.text or "", str(r.doc_id)) for r in kept.collect()) == sorted((t, str(i)) for t, i in top.items())


def test_exact_index_over_batches(spark):
    index = exact.DigestIndex.create(spark)
    take = lambda rows: {r.doc_id: (r.keep_id, r.group_size, r.kept) for r in exact.deduplicate(docs_frame(spark, rows), index, batches=1).collect()}
    assert take([(1, "a"), (2, "a"), (3, "b")]) == {1: (2, 2, False), 2: (2, 2, True), 3: (3, 1, True)}
    assert take([(4, "a"), (6, "c"), (5, "c")]) == {4: (4, 3, True), 5: (6, 2, False), 6: (6, 2, True)}
    assert take([(0, "a"), (7, "b")]) == {0: (4, 4, False), 7: (7, 2, True)}
    state = {(r.keep_id, r.seen, r.born) for r in index.rows().collect()}
    assert state == {(4, 4, 1), (7, 2, 1), (6, 2, 2)}
    assert len(index.runs.spans()) <= exact.FAN_IN  # merged on the way
    again = exact.DigestIndex(spark, index.location, index.buckets, "BIGINT")  # another session would attach like this
    assert {(r.keep_id, r.seen, r.born) for r in again.rows().collect()} == state
    # a text that an earlier batch brought is no row of a later one
    assert [r.doc_id for r in exact.unique_rows(docs_frame(spark, [(8, "a"), (9, "d"), (10, "d")]), again).collect()] == [10]


def test_exact_batches_can_be_taken_in_again(spark):
    index = exact.DigestIndex.create(spark)
    rows = [(spark.createDataFrame([(i, t) for i, t in part], "id long, t string").select("id", exact.text_digest(F.col("t")).alias("digest"))) for part in ([(1, "a"), (2, "b")], [(3, "a"), (4, "c")])]
    index.ingest(rows[0])
    for _ in range(3):
        index.ingest(rows[1], 2)
    assert {(r.keep_id, r.seen, r.born) for r in index.rows().collect()} == {(3, 2, 1), (2, 1, 1), (4, 1, 2)}
    plan = index.runs.table((1, 1)).join(rows[1].select("digest"), "digest", "left_anti")._jdf.queryExecution().executedPlan().toString()
    assert "Bucketed: true" in plan


# 4


def test_hilbert_curve_visits_neighbours():
    for n, bits in ((2, 4), (3, 3)):
        cells = np.array(list(itertools.product(range(1 << bits), repeat=n)))
        h = sharding.hilbert_index(cells, bits)
        assert sorted(h) == list(range(len(cells)))
        walk = cells[np.argsort(h)]
        assert (np.abs(np.diff(walk, axis=0)).sum(axis=1) == 1).all()


def test_shards(spark, corpus, odd):
    docs = corpus.unionByName(odd.select(*corpus.columns))
    got = sharding.shards(docs, ["lang", "source", "n_chars"]).collect()
    rows = collected(docs)
    assert sorted(((r.doc_id, r["size"], r.text_crc32) for r in got), key=str) == sorted(((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in rows), key=str)
    by = defaultdict(list)
    for r in got:
        by[r.shard].append(r.slot)
        assert r.law == "rows" and r.grown_shard is None
    assert set(by) == set(range(16))
    sizes = [len(v) for v in by.values()]
    assert max(sizes) - min(sizes) <= 1
    assert all(sorted(v) == list(range(len(v))) for v in by.values())


def test_shards_prune(spark, sf, tmp_path):
    docs = table(spark, sf, "documents")
    path = str(tmp_path / "shards")
    sharding.write_shards(docs, path, ["lang", "n_chars"], count=8)
    back = spark.read.parquet(path)
    assert back.count() == docs.count()
    spread = back.groupBy("shard").agg(F.countDistinct("lang").alias("n")).agg(F.avg("n")).first()[0]
    assert spread < docs.select("lang").distinct().count()


def brute_cells(values, bits=8):
    """Cells of whole strings by the share of rows before them; null is cell 0."""
    top = (1 << bits) - 1
    known = sorted(v.encode() for v in values if v is not None)
    before = {v: known.index(v) for v in set(known)}
    return [0 if v is None else min(top, 1 + (before[v.encode()] + known.count(v.encode()) // 2) * top // len(known)) for v in values]


def brute_curve(a, b):
    """The place of (a, b) on a Hilbert curve of 256 x 256 points, by turning quadrants."""
    d, s = 0, 128
    while s:
        rx, ry = int(bool(a & s)), int(bool(b & s))
        d += s * s * ((3 * rx) ^ ry)
        if not ry:
            if rx:
                a, b = s - 1 - (a & (s - 1)), s - 1 - (b & (s - 1))
            a, b = b & (s - 1), a & (s - 1)
        s //= 2
    return d


def test_shards_against_brute_force(spark):
    """Order and shard of every row, over two columns of strings that share long prefixes, with nulls, ties and repeated ids."""
    rng = random.Random(21)
    names = [None, *(f"a-long-common-prefix-{n}" for n in range(40))]
    rows = [(rng.choice([None, *range(150)]), rng.choice(["x", "y z", None, "t" * 50]), rng.choice(names), rng.choice(names)) for _ in range(300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, a string, b string")
    cells = list(zip(brute_cells([r[2] for r in rows]), brute_cells([r[3] for r in rows]), strict=True))
    assert len(set(cells)) > 150  # common prefixes do not fall into one cell
    curve = sharding.hilbert_index(np.array(cells), 8).tolist()
    turned = {brute_curve(a, b) for a, b in cells}
    assert len(turned) == len(set(cells)) == len(set(curve))
    order = sorted(zip(curve, rows, strict=True), key=lambda v: (v[0], zlib.crc32((v[1][1] or "").encode()), len((v[1][1] or "").encode()), v[1][0] is not None, v[1][0] or 0))
    want = [(r[0], len((r[1] or "").encode()) + 1, zlib.crc32((r[1] or "").encode()), n * 7 // 300, n - -(-(n * 7 // 300) * 300 // 7)) for n, (_, r) in enumerate(order)]
    got = [(r.doc_id, r["size"], r.text_crc32, r.shard, r.slot) for r in sharding.shards(docs, ["a", "b"], 7).collect()]
    assert ordered(got) == ordered(want)


def test_written_shards_hold_every_row(spark, odd, empty, tmp_path):
    docs = docs_frame(spark, [(1, "a"), (1, "a"), (None, "b"), (None, None), (2, "")])
    for n, df in enumerate((docs, odd)):
        path = str(tmp_path / f"s{n}")
        shard = sharding.write_shards(df, path, ["lang", "n_chars"], 3)
        back = spark.read.parquet(path)
        assert shard == ("shard" if n == 0 else "shard_") and sorted(back.columns) == sorted([*df.columns, shard])
        assert ordered([tuple(r) for r in back.select(*df.columns).collect()]) == ordered([tuple(r) for r in df.collect()])
        sizes = [r["count"] for r in back.groupBy(shard).count().collect()]
        assert max(sizes) - min(sizes) <= 1
    sharding.write_shards(empty, str(tmp_path / "none"), ["lang"], 3)


# 5


def brute_substring(docs, window=50):
    split = lambda t: re.findall(r"[^\x20\x09-\x0D]+", t or "")
    first = {}
    for i, t in docs:
        w = split(t)
        for s in range(len(w) - window + 1):
            key = tuple(w[s : s + window])
            first[key] = min(i, first.get(key, i))
    out = []
    for i, t in docs:
        w, gone = split(t), set()
        for s in range(len(w) - window + 1):
            if first[tuple(w[s : s + window])] < i:
                gone.update(range(s, s + window))
        out.append((i, len(w), len(gone), hashlib.sha256(" ".join(x for k, x in enumerate(w) if k not in gone).encode()).hexdigest()))
    return out


@pytest.mark.parametrize("batches", [1, 2, 6])
def test_substring(spark, corpus, batches):
    docs = docs_frame(spark, [r for r in collected(corpus)] + [x for x in ODD if x[0] is not None])
    got = [tuple(r) for r in substring.deduplicate(docs, batches=batches, digest=True).collect()]
    want = brute_substring(collected(docs))
    assert ordered(got) == ordered(want)
    assert sum(g[2] for g in got) > 500


def test_substring_index_compacts(spark, corpus):
    """Batches against the runs of earlier ones, merged on the way; a batch that is taken in twice changes nothing."""
    index, got = substring.FingerprintIndex(spark, fan_in=2), []
    docs = corpus.where("doc_id < 200 or doc_id between 10000 and 10399")
    edges = [(0, 50), (50, 100), (100, 200), (10000, 10400)]
    for low, high in edges:
        part, before = docs.where(f"doc_id >= {low} and doc_id < {high}"), docs.where(f"doc_id < {low}")
        for _ in range(2 if low == 50 else 1):
            out = substring.deduplicate_batch(part, index, before if low else None, digest=True, number=edges.index((low, high)) + 1).collect()
        got += [tuple(r) for r in out]
        assert len(index.anchors.spans()) <= 2 and len(index.texts.spans()) <= 2
    assert ordered(got) == ordered(brute_substring(collected(docs)))


# 6


def test_pieces(spark, corpus, odd):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_proto=piece_model())
    docs = corpus.unionByName(odd.select(*corpus.columns))
    got = [tuple(r)[:4] for r in pieces.digests(docs.select("doc_id", "text"), piece_model(), keep=["doc_id"]).select("doc_id", "coded.*").collect()]
    want = []
    for i, t in collected(docs):
        ids = [1, *sp.encode(t or ""), 2]
        want.append((i, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(sp.decode(ids).encode()).hexdigest()))
    assert ordered(got) == ordered(want)


def test_piece_spans_cover_the_text(spark):
    c = pieces.codec(piece_model())
    rng = random.Random(2)
    alphabet = [*"abcthe  \n\t▁éñ中🙂\x00.,!", "the", "  ", "<0x0A>", "</s>", "\r\n", " \n"]
    for _ in range(500):
        t = "".join(rng.choice(alphabet) for _ in range(rng.randrange(14)))
        raw = t.encode()
        spans = c.spans(t)
        assert [s[0] for s in spans] == c.native.encode(t)
        assert [s[1] for s in spans[1:]] == [s[2] for s in spans[:-1]]
        assert not spans or (spans[0][1], spans[-1][2]) == (0, len(raw))
    row = pieces.encode(docs_frame(spark, [(1, "Hello  world"), (2, None)]), piece_model()).orderBy("doc_id").collect()
    assert row[0].coded.decoded == "Hello  world" and len(row[0].coded.ids) == len(row[0].coded.starts) and row[1].coded.ids == [1, 2]


@pytest.mark.parametrize("rule", ["nfkc", "nmt_nfkc", "nmt_nfkc_cf"])
def test_character_map_against_the_library(rule):
    import sentencepiece

    norm = sentencepiece.SentencePieceNormalizer(rule_name=rule, add_dummy_prefix=False, escape_whitespaces=False, remove_extra_whitespaces=False)
    proto = norm.serialized_model_proto()
    chars = dict(pieces._fields(dict(pieces._fields(proto))[3]))[2]
    found = pieces.CharacterMap(chars)
    rng = random.Random(4)
    alphabet = "abcXÉé①ﬁ中Ⅷ㌔ÅＡ１　\u00a0e\u0301ｶﾞ"
    for _ in range(300):
        t = "".join(rng.choice(alphabet) for _ in range(rng.randrange(1, 9)))
        raw, out, at = t.encode(), b"", 0
        while at < len(raw):
            got = found.longest(raw, at)
            size = 1 if raw[at] < 0x80 else 2 if raw[at] < 0xE0 else 3 if raw[at] < 0xF0 else 4
            n, new = got or (size, raw[at : at + size])
            out += new
            at += n
        assert out.decode() == norm.normalize(t)


# 7


def test_bands_are_minhash():
    rng = random.Random(6)
    hits = n = 0
    for _ in range(200):
        a = "".join(rng.choice("abcdefgh ") for _ in range(200))
        b = list(a)
        b[rng.randrange(200)] = "#"
        b = "".join(b)
        if lines.jaccard(a, b) >= 0.8:
            (x, y), (s, t) = lines.bands([a, b])
            n += 1
            hits += bool((x == y).any()) and int(s ^ t).bit_count() <= lines.APART
    assert n > 100 and hits / n >= 0.98


def test_lines(spark, corpus, odd):
    rng = random.Random(7)
    long = "the quick brown fox jumps over the lazy dog while many other animals look on and wonder what it is about " * 2
    near = [long.strip(), long.strip()[:-1] + "!", "x" + long.strip()[1:]]
    other = "".join(rng.choice("abcdefghij ") for _ in range(120))
    docs = docs_frame(spark, [(1, f"{near[0]}\n{other}\n\nshort"), (2, f"{near[1]}\nshort\n{other}"), (3, f"unlike\n{near[2]}"), (4, None), (4, None), (None, "short")])
    got = {(r.doc_id, r.kept): r for r in lines.deduplicate(docs).collect()}
    kept = {k[0]: k[1] for k in got}
    assert kept[1] == f"{near[0]}\n{other}\n\nshort" and kept[2] == "" and kept[3] == "unlike" and kept[4] == "" and kept[None] == ""


def test_similar_lines_of_documents_are_candidates(spark, sf):
    """Recall of the candidates over pairs of real lines at and little above the threshold."""
    rng, near, n = random.Random(9), 0, 0
    texts = [x for r in table(spark, sf, "documents").collect() for x in (r.text or "").split("\n") if len(x) > 60]
    for x in texts[:1500]:
        words = x.split(" ")
        other = list(words)
        for _ in range(max(1, len(words) // 24)):
            other[rng.randrange(len(words))] = rng.choice(rng.choice(texts).split(" "))
        y = " ".join(other)
        if 0.8 <= lines.jaccard(x, y) < 0.86:
            (a, b), (s, t) = lines.bands([x, y])
            n += 1
            near += bool((a == b).any()) and int(s ^ t).bit_count() <= lines.APART
    assert n > 150 and near / n >= 0.98


def test_lines_of_one_crowded_bucket(spark):
    """Near copies of two originals in one bucket: all are linked, and the pairs compared grow with the lines, not with their square."""
    rng = random.Random(10)
    two = ["".join(rng.choice("abcdefghijklmnop ") for _ in range(300)) for _ in range(2)]
    copies = []
    for o, base in enumerate(two):
        for _ in range(300):
            at = rng.randrange(20, 280)
            copies.append(base[:at] + rng.choice("QRSTUVWXYZ") + base[at + 1 :])
    rng.shuffle(copies)
    copies = list(dict.fromkeys(copies))
    _, sketch = lines.bands(copies)
    rows = [(7, i, int(s)) for i, s in enumerate(sketch)]
    frame = spark.createDataFrame(rows + rows[::3], "key long, lid long, sketch long")
    pairs = lines.candidates(frame).collect()
    leaders = {r.leader for r in pairs}
    assert len(leaders) < 12 and len(pairs) <= len(copies) * len(leaders)
    kept = lines.deduplicate(docs_frame(spark, [(i, x) for i, x in enumerate(copies)])).collect()
    assert sorted(r.n_removed for r in kept) == [0, 0] + [1] * (len(copies) - 2)


def test_lines_around_one_original(spark, monkeypatch):
    """Copies that are like their original but not like each other, and the original not the leader: linked without all pairs."""
    rng, seen = random.Random(12), []
    base = "".join(rng.choice("abcdefghijklmnop ") for _ in range(200))
    copies = [base]
    for _ in range(150):
        t = list(base)
        for at in (rng.randrange(5, 60), rng.randrange(70, 125), rng.randrange(135, 195)):
            t[at] = rng.choice("QRSTUVWXYZ0123456789")
        copies.append("".join(t))
    copies = [base, *(c for c in dict.fromkeys(copies[1:]) if lines.jaccard(base, c) >= 0.8)]
    assert len(copies) > 100 and sum(lines.jaccard(a, b) < 0.8 for a, b in itertools.combinations(copies[1:], 2)) > 0.9 * len(copies) ** 2 / 2
    real = lines._compared
    monkeypatch.setattr(lines, "_compared", lambda pairs, texts, shingle: seen.append(pairs.count()) or real(pairs, texts, shingle))
    got = lines.deduplicate(docs_frame(spark, list(enumerate(copies)))).collect()
    assert sum(r.n_removed for r in got) == len(copies) - 1
    assert sum(seen) < 20 * len(copies)


def test_lines_near_but_not_similar(spark, monkeypatch):
    """Lines of one origin that are all a little under the threshold: few of their pairs are compared, and a similar pair among them is found."""
    rng, seen = random.Random(14), []
    base = "".join(rng.choice("abcdefghijklmnop ") for _ in range(300))
    copies = []
    for _ in range(240):
        t = list(base)
        for at in (5, 65, 125, 185, 245):
            t[at + rng.randrange(50)] = rng.choice("QRSTUVWXYZ0123456789")
        copies.append("".join(t))
    copies.append(copies[7] + "!")
    sets = [{x[i : i + 5] for i in range(len(x) - 4)} for x in copies]
    root, below = list(range(len(copies))), 0
    for a, b in itertools.combinations(range(len(copies)), 2):
        like = len(sets[a] & sets[b]) / len(sets[a] | sets[b])
        below += 0.6 < like < 0.8
        if like >= 0.8:
            x, y = root[a], root[b]
            root = [min(x, y) if r in (x, y) else r for r in root]
    assert below > 0.6 * len(copies) ** 2 / 2
    real = lines._compared
    monkeypatch.setattr(lines, "_compared", lambda pairs, texts, shingle: seen.append(pairs.count()) or real(pairs, texts, shingle))
    got = {r.doc_id: r.n_removed for r in lines.deduplicate(docs_frame(spark, list(enumerate(copies)))).collect()}
    assert {i for i, n in got.items() if n} == {i for i, r in enumerate(root) if r != i} and got[240] == 1
    assert sum(seen) < 0.2 * below


def test_similarities_are_exact():
    rng = random.Random(15)
    some = ["", "a", "abcd", "abcde", "abcdee", "aaaaaaaaaa", "aaaaaaaaab", "Straße ñ ü", "中文 🙂 und mehr Text", "中文 🙂 und mehr Texte"]
    some += ["".join(rng.choice("abc ") for _ in range(rng.randrange(1, 60))) for _ in range(60)]
    left, right = zip(*itertools.product(some[1:], repeat=2), strict=True)
    assert lines.similarities(list(left), list(right)) == [lines.jaccard(a, b) for a, b in zip(left, right, strict=True)]
    n, maps = lines.bit_maps(some[1:])
    sets = [{x[i : i + 5] for i in range(max(1, len(x) - 4))} for x in some[1:]]
    assert n.tolist() == [len(s) for s in sets]
    for (s, x), (t, y) in itertools.combinations(zip(sets, maps, strict=True), 2):
        assert np.bitwise_count((x ^ y).view(np.uint64)).sum() <= len(s ^ t)


def test_lines_against_all_pairs(spark, sf):
    rows = [(r.doc_id, r.text) for r in table(spark, sf, "documents").where("n_chars < 1500").limit(60).collect()]
    occ = [(i, n, x) for i, t in sorted(rows) for n, x in enumerate(t.split("\n")) if x and not x.isspace()]
    root = list(range(len(occ)))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    sets = [{x[k : k + 5] for k in range(max(1, len(x) - 4))} for _, _, x in occ]
    for a, b in itertools.combinations(range(len(occ)), 2):
        if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    want = defaultdict(int)
    for k, (i, _, _) in enumerate(occ):
        want[i] += find(k) != k
    got = {r.doc_id: r.n_removed for r in lines.deduplicate(docs_frame(spark, rows)).collect()}
    assert {i: n for i, n in got.items() if n} == {i: n for i, n in want.items() if n}


# 8


def test_quality(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = table(spark, sf, "documents"), table(spark, sf, "labels")
    learn = labels.where("doc_id % 3 != 0")
    model = quality.train(docs, learn)
    got = quality.score(docs, model).select("doc_id", "quality.*").join(labels.where("doc_id % 3 = 0"), "doc_id").collect()
    right = [r.accepted == (r.quality == 1) for r in got]
    clean = [r.accepted for r in got if r.quality == 1]
    assert sum(right) / len(right) > 0.93 and sum(clean) / len(clean) > 0.96
    assert model.rounds


def test_quality_against_a_plain_twin(spark, sf):
    """The registered query against co-training by loops over all documents at once."""
    import pyarrow as pa

    docs = table(spark, sf, "documents")
    rows = docs.select("*", quality._spot("doc_id", "quality sample").alias("q"), *(quality._spot("doc_id", f"round {r}").alias(f"r{r}") for r in range(quality.ROUNDS))).orderBy("doc_id").toArrow().combine_chunks()
    batch = rows.to_batches()[0]
    t, m = quality._features(batch, "text", ["lang", "source", "n_chars"])
    label = {r.doc_id: r.quality for r in table(spark, sf, "labels").collect()}
    ids = rows.column("doc_id").to_pylist()
    have = [n for n, i in enumerate(ids) if i in label]
    assert len(have) < quality.LABELLED
    y = np.array([float(label[ids[n]]) for n in have])
    part = np.arange(len(have)) % 3 == 0
    views, sets = [t, m], [([n for n, h in zip(have, part) if not h], list(y[~part])) for _ in (0, 1)]
    taken = {ids[n] for n in have}
    for r in range(quality.ROUNDS):
        models = [quality.fit(v[np.array(s[0])], np.array(s[1])) for v, s in zip(views, sets, strict=True)]
        spot, chosen = rows.column(f"r{r}").to_pylist(), []
        for i in (0, 1):
            p = 1 / (1 + np.exp(-np.clip(models[i].logit(views[i]), -30, 30)))
            sure = sorted((spot[n], str(ids[n]), n) for n in range(len(ids)) if ids[n] not in taken and max(p[n], 1 - p[n]) >= quality.SURE)[: quality.HANDED]
            chosen.append([(n, float(p[n] > 0.5)) for _, _, n in sure])
        for i in (0, 1):
            sets[1 - i][0].extend(n for n, _ in chosen[i])
            sets[1 - i][1].extend(v for _, v in chosen[i])
            taken |= {ids[n] for n, _ in chosen[i]}
        if not chosen[0] and not chosen[1]:
            break
    assert len(sets[0][0]) + len(sets[1][0]) > 2 * (~part).sum()  # something was handed over
    models = [quality.fit(v[np.array(s[0])], np.array(s[1])) for v, s in zip(views, sets, strict=True)]
    logits = [model.logit(v) for model, v in zip(models, views, strict=True)]
    held = np.array(have)[part]
    both = quality.fit(np.column_stack([x[held] for x in logits]), y[part])
    want = dict(zip(ids, 1 / (1 + np.exp(-np.clip(both.logit(np.column_stack(logits)), -30, 30))), strict=True))
    got = {r.doc_id: (r.score, r.accepted) for r in queries()["op8_quality"](spark, sf).collect()}
    assert set(got) == set(want) and isinstance(batch, pa.RecordBatch)
    for i, (score, accepted) in got.items():
        assert abs(score - want[i]) < 1e-6 and accepted == (score >= quality.CUT)


def test_quality_without_examples(spark, empty):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    docs = docs_frame(spark, ODD)
    assert all(r.quality.accepted for r in quality.score(docs, quality.train(docs, none)).collect())
    assert quality.score(empty, quality.train(empty, none)).count() == 0


# 9


def test_language(spark):
    out = [r for r in queries()["op9_language"](spark, "/root/testdata/sf0.01").collect()]
    lang = {r.doc_id: r.lang for r in table(spark, "/root/testdata/sf0.01", "documents").collect()}
    held = [r for r in out if r.held_out and lang[r.doc_id]]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and 0 <= r.score <= 1 for r in out)
    assert sum(r.lang_pred == lang[r.doc_id] for r in held) / len(held) > 0.95


def test_forward_sums_all_segmentations():
    rng = np.random.default_rng(0)
    rows = {p: i for i, p in enumerate(["▁", "▁t", "▁th", "t", "h", "e", "th", "he", "the", "▁the", "n"])}
    probs = np.vstack([rng.random((len(rows), 2)), np.full(2, 1e-7)])
    scorer = langid.Scorer(langid.Model(["a", "b"], np.zeros(2), rows, probs))

    def total(w):
        if not w:
            return np.ones(2)
        out = np.zeros(2)
        for k in range(1, len(w) + 1):
            r = rows.get(w[:k], len(rows) if k == 1 else None)
            if r is not None:
                out = out + probs[r] * total(w[k:])
        return out

    words = ["the", "then", "hethe", "xt", "thethethethethetheth"]
    assert np.allclose(scorer.many(words), np.log([total("▁" + w) for w in words]))


def test_language_against_a_plain_twin(spark, sf):
    """The registered query against counts and sums over all segmentations by loops."""
    c = pieces.codec(piece_model())
    rows = [(r.doc_id, r.text, r.lang) for r in table(spark, sf, "documents").select("doc_id", "text", "lang").collect()]
    held = lambda i: i is not None and zlib.crc32(str(i).encode()) % 5 == 0
    learn = [(t, g) for i, t, g in rows if not held(i) and t is not None and g is not None]
    names = sorted({g for _, g in learn})
    sizes = {g: sum(h == g for _, h in learn) for g in names}
    assert max(sizes.values()) < langid.SAMPLE
    usable = sorted(c.ids.values())
    weight = {g: dict.fromkeys(usable, langid.SMOOTH) for g in names}
    for t, g in learn:
        for i in c.native.encode(" ".join(t.split())):
            if i in weight[g]:
                weight[g][i] += 1
    chance = {g: {c.pieces[i]: w / sum(weight[g].values()) for i, w in weight[g].items()} for g in names}
    longest = max(map(len, c.ids))
    memo = {}

    def word(w):
        if w not in memo:
            text, out = pieces.SPACE + w, []
            for g in names:
                way = [1.0] + [0.0] * len(text)
                for end in range(1, len(text) + 1):
                    for begin in range(max(0, end - longest), end):
                        p = chance[g].get(text[begin:end], langid.UNKNOWN if end - begin == 1 else 0.0)
                        way[end] += way[begin] * p
                out.append(np.log(max(way[-1], 1e-300)))
            memo[w] = np.array(out)
        return memo[w]

    got = {r.doc_id: r for r in queries()["op9_language"](spark, sf).collect()}
    some = [r for r in rows if r[1] and any(map(str.isalpha, r[1])) and max(map(len, r[1].split())) < 60][:60]
    prior = np.log([(sizes[g] + 1) / (len(learn) + len(names)) for g in names])
    for i, t, _ in some:
        logs = sum((word(w) for w in t.split()), prior)
        best = int(np.argmax(logs))
        assert got[i].lang_pred == names[best] and abs(got[i].score - 1 / np.exp(logs - logs[best]).sum()) < 1e-6
    assert len(some) == 60


# 10


def brute_url(url, rules):
    host = path = ""
    if url and "://" in url:
        m = re.match(r"([^/?#]*)([^?#]*)", url.split("://", 1)[1], re.S)
        host, path = re.sub("[A-Z]", lambda x: x[0].lower(), m[1]), m[2]
    fits = [(len(h + p), h + p, v) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fits, default=None)
    return host, path, best and best[1], best[2] if best else "allow"


@pytest.mark.parametrize("limit", [10, 0])
def test_urls(spark, sf, limit):
    urls = [r.url for r in table(spark, sf, "pages").collect()]
    urls += [None, "", "nope", "http://NET/", "http://a.b.Example.NET/en/x?y#z", "http://example.net", "http://xexample.com/de/", "a://b://net/", "http://example.com/de", "http://example.com/de/\nx", "ftp://org/fr/", "http://org/fr/", "http://a..net/", "http://.net/", "http://net?x/", "http://Éxample.net/en/"] + ["http://net/"] * 3
    frame = spark.createDataFrame(list(enumerate(urls)) + [(0, urls[0]), (None, "http://net/")], "page_id long, url string")
    rules = urlfilter.RULES + [("net", "/en", "block")]
    got = [tuple(r) for r in urlfilter.judge(frame, urlfilter.rules_table(spark, rules), broadcast_rules=limit).collect()]
    want = [(r.page_id, *brute_url(r.url, rules)) for r in frame.collect()]
    assert ordered(got) == ordered(want)
    assert all(v == "allow" and r is None for _, _, _, r, v in urlfilter.judge(frame, urlfilter.rules_table(spark).where("false")).collect())


def test_urls_long_and_with_clashing_columns(spark):
    urls = ["http://net/" + "x" * 200_000, "h" * 200_000, "http://" + "a." * 5_000 + "net/", "http://" + "n" * 100_000 + ".org/fr/"]
    frame = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").withColumns({n: F.lit("mine") for n in ("i", "u", "n", "host", "path", "rule", "verdict", "e", "full", "short", "best", "copy", "rule_host")})
    got = [tuple(r) for r in urlfilter.judge(frame, urlfilter.rules_table(spark)).collect()]
    assert ordered(got) == ordered((i, *brute_url(u, urlfilter.RULES)) for i, u in enumerate(urls))


# all


def test_odd_rows_and_names(spark, sf, odd):
    bench = table(spark, sf, "benchmark")
    assert decontaminate.decontaminate(odd, bench).count() == odd.count()
    assert pieces.digests(odd, piece_model()).count() == odd.count()
    assert decontaminate.decontaminate(odd, bench, block_bytes=2500).count() == odd.count()
    assert exact.unique_rows(odd, exact.DigestIndex.create(spark)).columns == odd.columns
    assert simhash.one_of_each(odd).columns == odd.columns
    model = quality.train(odd, table(spark, sf, "labels"))
    assert quality.score(odd, model).count() == odd.count()
    lang = langid.train(odd, piece_model())
    rows = langid.predict(odd.select("doc_id", "text"), lang).collect()
    assert {r.doc_id: r.language.lang_pred for r in rows}[1] == "und"
    assert lines.deduplicate(odd).count() == odd.count()
    assert substring.deduplicate(odd).count() == odd.count()
    assert sharding.shards(odd, ["lang", "n_chars"], 16).count() == odd.count()


def test_empty_tables(spark, sf, empty):
    bench = table(spark, sf, "benchmark")
    assert decontaminate.decontaminate(empty, bench).count() == 0
    assert decontaminate.decontaminate(docs_frame(spark, ODD), bench.where("false")).where("overlap.contaminated").count() == 0
    assert simhash.near_duplicates(empty).count() == 0
    assert simhash.one_of_each(empty).count() == 0
    assert exact.deduplicate(empty, exact.DigestIndex.create(spark)).count() == 0
    assert sharding.shards(empty, ["lang"]).count() == 0
    assert substring.deduplicate(empty).count() == 0
    assert pieces.digests(empty, piece_model()).count() == 0
    assert lines.deduplicate(empty).count() == 0
    assert langid.predict(empty, langid.train(empty, piece_model())).count() == 0
    assert urlfilter.judge(spark.createDataFrame([], "page_id long, url string"), urlfilter.rules_table(spark)).count() == 0


def brute_similar(docs, shingle=5, similar=(4, 5)):
    """Ids that stay: the least of each class of texts whose word shingles have a Jaccard similarity of 0.8 or more."""
    sets = []
    for _, t in docs:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets.append({" ".join(w[k : k + shingle]) for k in range(max(1, len(w) - shingle + 1))} if w else set())
    root = list(range(len(docs)))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for a, b in itertools.combinations(range(len(docs)), 2):
        if similar[1] * len(sets[a] & sets[b]) >= similar[0] * len(sets[a] | sets[b]):
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    least = {}
    for k, (i, _) in enumerate(docs):
        least[find(k)] = min(i, least.get(find(k), i))
    return set(least.values())


def test_near_stage_reaches_its_similarity(spark, sf, corpus):
    import corpus_pipeline

    rng = random.Random(11)
    base = [t.split() for _, t in collected(corpus) if len((t or "").split()) > 100][:6]
    planted = [(30_000 + 100 * i + n, " ".join(mutated(rng, w, max(1, round(len(w) * n / 400))))) for i, w in enumerate(base) for n in range(1, 13)]
    odd = [(i + 50_000, t) for i, t in ODD if i is not None]
    docs = corpus.unionByName(docs_frame(spark, planted + odd))
    got = [r.doc_id for r in corpus_pipeline.STAGES[2][1](spark, docs, sf).collect()]
    assert sorted(got) == sorted(brute_similar(collected(docs)))
    # near copies that are more than two bits apart
    assert len(got) < len({c for _, _, c in brute_simhash(collected(docs))})


def test_near_stage_of_crowded_buckets(spark):
    rng = random.Random(12)
    base = [f"b{i}" for i in range(60)]
    rows = [(i, " ".join(mutated(rng, base, rng.randrange(1, 4)))) for i in range(120)] + [(200 + i, " ".join(base[:20] + [f"u{rng.randrange(10**6)}" for _ in range(60)])) for i in range(40)]
    docs = docs_frame(spark, rows)
    got = [r.doc_id for r in similar.one_of_each(docs).collect()]
    assert sorted(got) == sorted(brute_similar(rows))
    assert 40 < len(got) < len(rows)


def test_near_stage_links_by_fingerprints(spark, corpus, monkeypatch):
    docs = collected(corpus)
    blobs = pa.array([t for _, t in docs], pa.string())
    doc, h = similar.shingle_hashes(*kernels.text_bytes(blobs))
    got = similar.fingerprints(doc, h, len(docs)).view(np.uint64).tolist()
    for n, bits in enumerate(got):
        mine = h[doc == n].view(np.uint8).reshape(-1, 8)
        assert np.array([bits], np.uint64).tobytes() == np.packbits(2 * np.unpackbits(mine, axis=1).sum(axis=0, dtype=int) > len(mine)).tobytes()
    # pairs within two bits are linked by the ring, and their texts are compared
    each = spark.createDataFrame([(b - (b >> 63 << 64), i) for i, b in enumerate(got)], "bits long, lid long")
    met = {(r.a, r.b) for r in similar.by_fingerprint(each).collect()}
    head = {b: min(i for i, c in enumerate(got) if c == b) for b in got}
    ring = {(max(i, j), min(i, j)) for b, i in head.items() for c, j in head.items() if i != j and (b ^ c).bit_count() <= 2}
    assert met == ring | {(i, head[b]) for i, b in enumerate(got) if i != head[b]}
    calls, links = [], similar.simhash.links
    monkeypatch.setattr(similar.simhash, "links", lambda d, *a: calls.append(1) or links(d, *a))
    assert sorted(r.doc_id for r in similar.one_of_each(corpus).collect()) == sorted(brute_similar(docs)) and calls


def test_cross_pairs_meet_once(spark):
    """Two texts of 400 shingles that share the first forty keys are one row, not one for each bucket that they fit in."""
    keys = list(range(40))
    rows = [(k, lid, k, lid, 400, keys, *[0] * similar.MAPS) for lid in (1, 2) for k in keys]
    left = spark.createDataFrame(rows, "key long, lid long, at long, c long, n int, keys array<long>, " + ", ".join(f"{c} long" for c in similar.CELLS))
    got = similar.cross_pairs(left.withColumn("back", similar._back("keys", "at")), Fraction(4, 5)).collect()
    assert [(r.a, r.b) for r in got] == [(2, 1)]


def test_quality_features_take_little_memory():
    import tracemalloc

    texts = ["some words of a text that is cut, 123 " * 60] * 2000  # 4.6 MB
    batch = pa.RecordBatch.from_arrays([pa.array(texts), pa.array([1] * len(texts))], names=["t", "n"])
    tracemalloc.start()
    try:
        assert sum(p.num_rows for p, _ in quality._parts(batch, "t", ["n"])) == len(texts)
        assert tracemalloc.get_traced_memory()[1] < 80 << 20
    finally:
        tracemalloc.stop()


def test_decontamination_takes_little_memory():
    import tracemalloc

    item = "one two three four five six seven eight nine ten"
    block = decontaminate.Block([("a", item)], 10, 3)
    batch = pa.RecordBatch.from_arrays([pa.array([f"{item} and other words of a text that is not short " * 23] * 2000)], names=["t"])  # 4.6 MB
    tracemalloc.start()
    try:
        (found,) = decontaminate._tally([batch], "t", block.distinct())
        assert found.column("n").to_pylist() == [2000 * 23] * 8
        assert tracemalloc.get_traced_memory()[1] < 40 << 20
    finally:
        tracemalloc.stop()


def test_pipeline_against_brute_force(spark, sf):
    """Every stage by loops; near duplicates are texts of similarity 0.8 over five words, as stages without a contract of their own take."""
    import corpus_pipeline

    docs = table(spark, sf, "documents")
    got = [tuple(r)[:4] for r in corpus_pipeline.run(spark, sf).collect()]
    model = quality.train(docs, table(spark, sf, "labels"))
    rows = [(r.doc_id, r.text) for r in quality.score(docs, model).where("quality.accepted").collect()]
    last = {}
    for i, t in rows:
        last[t] = max(i, last.get(t, i))
    rows = [(i, t) for i, t in rows if last[t] == i]
    kept = brute_similar(rows)
    assert kept < {i for i, _ in rows}
    rows = [r for r in rows if r[0] in kept]
    items = [(r.item_id, r.text) for r in table(spark, sf, "benchmark").collect()]
    rows = [r for r, o in zip(rows, brute_overlap(rows, items), strict=True) if not o[5]]
    c = pieces.codec(piece_model())
    want = []
    for i, t in rows:
        ids = [1, *c.native.encode(t), 2]
        want.append((i, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(c.native.decode(ids).encode()).hexdigest()))
    assert ordered(got) == ordered(want)


def test_pipeline_stages_take_odd_tables(spark, sf, odd, empty):
    """Each stage but the last gives the columns it gets, clashing ones too, and takes odd rows and empty tables."""
    import corpus_pipeline

    for docs in (odd, empty.withColumns({n: F.lit("mine") for n in ("quality", "overlap", "rank", "winner", "own_digest")})):
        for name, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, docs, sf)
            assert out.columns == docs.columns, name
            assert out.count() <= docs.count()
        assert corpus_pipeline.STAGES[-1][1](spark, docs, sf).count() == docs.count()
