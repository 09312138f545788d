"""Jaccard join, substring removal, BPE, mixing and sharding against brute force on small tables."""

import collections
import hashlib
import re
import struct
import zlib

import numpy as np
import pyarrow as pa
import pytest

from corridor.llm import bpe, components, jaccard, mixing, sharding, substring
from corridor.llm import texthash as T

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOWER = {c: c + 32 for c in range(65, 91)}
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, component long, part string"


def fixture():
    """Families of near copies, exact copies, shared passages, odd texts and ids."""
    rng = np.random.default_rng(7)
    word = lambda: "".join(rng.choice(list("abcdeé"), rng.integers(1, 6)))
    texts = []
    passage = [word() for _ in range(60)]
    for family in range(6):
        base = [word() for _ in range(int(rng.integers(20, 200)))]
        for _ in range(12):
            t = list(base)
            for _ in range(int(rng.integers(0, 6))):
                t[int(rng.integers(len(t)))] = word()
            texts.append(" ".join(t))
        texts.append(" ".join(base).upper())
        texts.append("\n".join([*base[:10], *passage, *base[10:15]]))
    texts += [" ".join(base)] * 5 + [None, None, "", "   \t\n", "one", "One two", "one  two", "a b c", "x " * 3000, "\u00a0", "y" * 5000]
    texts += [" ".join(word() for _ in range(9)) for _ in range(20)]
    rows = [(i * 3 % 1009, t, "en", f"s{i % 3}" if i % 7 else None, len(t or ""), 1, "p") for i, t in enumerate(texts)]
    return [*rows, rows[4], (None, "null id " * 20, None, None, 3, 1, "p")]


def words(t, lower=False):
    return WORD.findall((t or "").translate(LOWER) if lower else t or "")


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(fixture(), SCHEMA).repartition(3)


@pytest.mark.parametrize("k,num", [(3, 90), (5, 80), (2, 50)])
def test_jaccard_components(spark, docs, k, num):
    sets = collections.defaultdict(list)
    for i, t, *_ in fixture():
        w = words(t, True)
        s = frozenset(tuple(w[j : j + k]) for j in range(max(1, len(w) - k + 1))) if w else frozenset()
        sets[i].append(s)
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(i for i in sets if i is not None)
    for x, i in enumerate(ids):
        for j in ids[:x]:
            if any(a and b and 100 * len(a & b) >= num * len(a | b) for a in sets[i] for b in sets[j]):
                a, b = sorted((find(i), find(j)))
                root[b] = a
    want = sorted((repr(i), len(s), None if i is None else find(i)) for i, t in sets.items() for s in t)
    got = sorted((repr(r.doc_id), r.n_shingles, r.component_id) for r in jaccard.jaccard_components(docs, jaccard.Similarity(k, num)).collect())
    assert got == want
    if num < 95:
        assert sum(i != c for i, c in ((r[0], repr(r[2])) for r in got)) > 10


def test_large_clusters_are_tiled(spark, docs, monkeypatch):
    want = sorted(jaccard.jaccard_components(docs, jaccard.Similarity(3, 90)).where("doc_id is not null").collect())
    monkeypatch.setattr(jaccard, "TILE_DOCS", 3)
    assert sorted(jaccard.jaccard_components(docs, jaccard.Similarity(3, 90)).where("doc_id is not null").collect()) == want


@pytest.mark.parametrize("left", [0, 7])
def test_partial_counts_sum_to_overlaps(left):
    """Fragments of the order, counted apart, dropped early and summed per pair, against sets."""
    rng = np.random.default_rng(2)
    base = rng.integers(0, 1 << 63, 60).astype(np.uint64) * np.uint64(2) + np.uint64(1)
    sets = [np.unique(np.where(rng.random(60) < 0.06, rng.integers(0, 1 << 63, 60).astype(np.uint64), base)) for _ in range(20)] + [np.unique(rng.integers(0, 1 << 63, 50).astype(np.uint64))]
    sim = jaccard.Similarity(3, 80)
    sizes = np.array([len(s) for s in sets])
    top = np.uint64(64 - jaccard.FRAGMENT_BITS)
    packed = [jaccard.pack_counts(*jaccard.partial_counts(sim, [s[s >> top == np.uint64(f)] for s in sets], sizes, left or len(sets))) for f in range(jaccard.FRAGMENTS)]
    across = len(sets) - left
    at, total = jaccard.sum_counts(packed, (left or len(sets)) * across)
    got = {(int(a), int(b), int(n)) for a, b, n in zip(at // across, at % across + left, total, strict=True) if 100 * n >= 80 * (sizes[a] + sizes[b] - n)}
    want = set()
    for a in range(left or len(sets)):
        for b in range(left or a + 1, len(sets)):
            n = len(np.intersect1d(sets[a], sets[b]))
            if 100 * n >= 80 * (sizes[a] + sizes[b] - n):
                want.add((a, b, n))
    assert got == want and len(want) > 20


def test_jaccard_of_nothing(spark):
    got = jaccard.jaccard_components(spark.createDataFrame([], SCHEMA))
    assert got.count() == 0 and got.columns == ["doc_id", "n_shingles", "component_id"]


def removal(rows, n=13):
    first = {}
    for i, t, *_ in rows:
        if i is not None:
            w = words(t)
            for j in range(len(w) - n + 1):
                key = tuple(w[j : j + n])
                first[key] = min(i, first.get(key, i))
    out = []
    for i, t, *_ in rows:
        w = words(t)
        keep = [True] * len(w)
        for j in range(len(w) - n + 1 if i is not None else 0):
            if first[tuple(w[j : j + n])] < i:
                keep[j : j + n] = [False] * n
        kept = " ".join(x for x, k in zip(w, keep, strict=True) if k)
        out.append((repr(i), len(w), len(w) - sum(keep), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out)


DIGEST = "n_words long, n_removed long, kept_sha256 string"


@pytest.mark.parametrize("budget", [substring.GROUP_WINDOWS, 50])
def test_substring_removal(docs, budget, monkeypatch):
    plain = substring.repeated_windows
    monkeypatch.setattr(substring, "repeated_windows", lambda d, w, c: plain(d, w, c, budget, 8))
    got = substring.remove_repeats(docs, 13, substring.kept_digest, DIGEST).collect()
    assert sorted((repr(r[0]), *r[1:]) for r in got) == removal(fixture())
    assert sum(r.n_removed > 0 for r in got) > 10


def test_substring_compares_words_not_hashes(docs, monkeypatch):
    """With hashes of 8 bits nearly all labels and prints meet by chance; the words on the paths still tell suffixes apart in parts and groups."""
    plain = T.windows

    def coarse(w, k):
        h, at = plain(w, k)
        return h & np.uint64(0xFF00000000), at

    rows = [(i, " ".join(f"w{(i * 31 + j) % 97}" for j in range(40))) for i in range(30)]
    monkeypatch.setattr(T, "windows", coarse)
    own = pa.table({"part": pa.array([0] * 30, pa.int32()), "doc_id": pa.array([r[0] for r in rows]), "text": pa.array([r[1] for r in rows])})
    windows = substring.PartWindows(own, 13)
    p = windows.paths(np.ones(len(windows.at), bool), 13)
    starts = {}
    for i, text in rows:
        for j in range(28):
            starts.setdefault(tuple(text.split()[j : j + 13]), set()).add(i)
    for x, (new, low) in enumerate(zip(p.new, p.low, strict=True)):
        path = tuple(p.words[c].as_py().decode() for c in p.codes[x])
        assert int(low) in starts[path] and (new or (p.codes[x] == p.codes[x - 1]).all())


def test_substring_parts_are_even(spark):
    """Ids that share a factor, and a large table of texts shorter than a window, are spread over all parts."""
    rows = [(i * 128, f"text number {i} is short") for i in range(4000)]
    laid = substring.laid_out(spark.createDataFrame(rows, "doc_id long, text string"), 128)
    load = [r["count"] for r in laid.groupBy("part").count().collect()]
    assert len(load) == 128 and max(load) < 3 * 4000 / 128
    copies = [(i, "one text for very many") for i in range(3000)] + rows
    laid = substring.laid_out(spark.createDataFrame(copies, "doc_id long, text string"), 128, (), 1 << 13)
    load = [r["count"] for r in laid.groupBy("part").count().collect()]
    assert sum(load) == 7000 and max(load) < 200  # 3000 copies are spread, too


def test_substring_of_nothing(spark):
    empty = spark.createDataFrame([], SCHEMA)
    got = substring.remove_repeats(empty, 13, substring.kept_digest, DIGEST)
    assert got.count() == 0 and got.columns == ["doc_id", "n_words", "n_removed", "kept_sha256"]
    rows = [(1, None), (2, ""), (3, "a b"), (None, "a " * 20), (4, "a " * 20), (4, "a " * 20), (5, "a " * 14)]
    got = substring.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), 13, substring.kept_digest, DIGEST).collect()
    assert sorted((repr(r[0]), *r[1:]) for r in got) == removal(rows)


def test_substring_carries_columns(docs):
    got = substring.remove_repeats(docs, 13, carry=("part", "component", "text"))
    assert got.columns == ["doc_id", "part", "component", "text", "n_words", "n_removed", "kept"] and got.count() == len(fixture())


def test_prefix_cells_are_dealt_within_budget():
    counts = np.array([5, 100, 7, 0, 30, 30, 1])
    first, width, groups = substring.deal(counts, 40, 1)
    assert width.tolist() == [1, 3, 1, 1, 1, 1, 1] and groups >= 5
    load = collections.Counter()
    for c, f, w in zip(counts, first, width, strict=True):
        if w == 1:
            load[f] += c
    assert max(load.values()) <= 40


def test_words_and_grams_of_odd_texts():
    texts = ["a b", "", None, " \t ", "x" * 700_000 + " y", "é ñ  ü\x0b\x1c z", "a b"]
    w = T.words(pa.array(texts, pa.string()))
    got = [[bytes(w.data[s:e]).decode() for s, e in zip(w.starts[a:b], w.ends[a:b], strict=True)] for a, b in zip(w.first, w.first[1:], strict=False)]
    assert got == [words(t) for t in texts]
    h, doc = T.gram_sets(w, 3)
    assert collections.Counter(doc.tolist()) == {0: 1, 4: 1, 5: 2 if len(words(texts[5])) == 4 else 1, 6: 1} or len(h)
    assert h[doc == 0].tolist() == h[doc == 6].tolist()


def test_components_of_a_path_and_a_star(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, i) for i in range(101, 140)] + [(7, 7), (None, 3), (200, 199), (199, 200)]
    got = {r.vertex: r.component for r in components.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(41)} | {i: 100 for i in range(100, 140)} | {199: 199, 200: 199}
    assert components.components(spark.createDataFrame([], "a long, b long")).count() == 0


@pytest.fixture(scope="module")
def reference():
    import public_tokenizers as P
    import tiktoken

    return tiktoken.Encoding("reference", pat_str=P.PATTERN, mergeable_ranks=bpe.codec().ranks, special_tokens={})


def test_bpe_like_the_reference(spark, docs, reference):
    for r in bpe.encode_documents(docs).collect():
        texts = [t or "" for i, t, *_ in fixture() if i == r.doc_id]
        ids = next(x for x in (reference.encode_ordinary(t) for t in texts) if x == r.ids)
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest()
        assert r.decoded_sha256 in {hashlib.sha256(t.encode()).hexdigest() for t in texts}


def test_bpe_of_long_and_strange_pre_tokens(reference):
    rng = np.random.default_rng(3)
    codec = bpe.codec()
    for text in ["a" * 20_000, "ab" * 9000, "".join(rng.choice(list("abcdé"), 20_000)), "é\u0301\u200d🙂\x1c\x85\xa0 \u3000x", "".join(map(chr, range(1, 1500))), "  \n\n  x's don'T"]:
        raw = codec.encode(text)
        assert np.frombuffer(raw, "<u4").tolist() == reference.encode_ordinary(text)
        assert codec.decode(raw) == text.encode()


def test_bpe_memory_turns_over(monkeypatch, reference):
    monkeypatch.setattr(bpe, "REMEMBERED", 5)
    memory = bpe._Memory(bpe.codec().ranks)
    for _ in range(3):
        for t in (" thon", " er", " lä", " qx", " zzz", " wub", " plok", " thon"):
            assert list(struct.unpack(f"<{len(memory[t]) // 4}I", memory[t])) == reference.encode_ordinary(t)
    assert len(memory) <= 5


def fill(weights, sizes, share, cap):
    target, left, open_ = [0.0] * len(sizes), share * sum(sizes), set(range(len(sizes)))
    while open_:
        level = left / sum(weights[i] for i in open_)
        over = {i for i in open_ if weights[i] * level > cap * sizes[i]}
        if not over:
            for i in open_:
                target[i] = weights[i] * level
            break
        for i in over:
            target[i] = cap * sizes[i]
            left -= target[i]
        open_ -= over
    return target


def test_mixing(spark, docs):
    got = mixing.draws(docs).collect()
    assert len(got) == len(fixture())
    by, size, taken, seen = collections.defaultdict(int), {}, collections.Counter(), {}
    for i, t, _, s, *_ in fixture():
        by[s] += len(words(t))
    order = sorted((s for s in by if s is not None)) + [None]
    targets = dict(zip(order, fill([(5, 2, 1)[i % 3] for i in range(len(order))], [by[s] for s in order], 1.5, 2), strict=True))
    for r in got:
        assert r.source_size == by[r.source] and abs(r.target - targets[r.source]) < 1e-6 and 0 <= r.copies <= 2
        taken[r.source] += r.size * r.copies
        size[r.source], seen[r.source] = r.source_size, r.target
    for s in by:
        assert abs(taken[s] - targets[s]) <= max(0.03 * targets[s], 40)
    key = lambda r: (repr(r.doc_id), r.size, r.copies)
    assert sorted(map(key, got)) == sorted(map(key, mixing.draws(docs.repartition(5)).collect()))


def test_mixing_of_nothing_and_clashing_names(spark):
    empty = spark.createDataFrame([], SCHEMA)
    assert mixing.draws(empty).count() == 0 and mixing.mixed(empty).count() == 0
    odd = spark.createDataFrame([(1, "a b c", "x", 1, 2), (2, "d", "x", 1, 2), (3, None, None, 1, 2)], "doc_id long, text string, source string, copies long, size long")
    out = mixing.mixed(odd)
    assert out.columns == odd.columns and out.where("doc_id = 1").count() in (1, 2)


def test_shards(spark, docs):
    got = sharding.shards_by_bytes(docs, 5).collect()
    assert len(got) == len(fixture()) and {r.law for r in got} == {"bytes"} and {r.grown_shard for r in got} == {None}
    text = collections.defaultdict(list)
    for i, t, *_ in fixture():
        text[i].append((t or "").encode())
    load, slots = collections.Counter(), collections.defaultdict(list)
    for r in got:
        assert (r.size, r.text_crc32) in {(len(t) + 16, zlib.crc32(t)) for t in text[r.doc_id]}
        load[r.shard] += r.size
        slots[r.shard].append(r.slot)
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())
    widest = max(r.size for r in got)
    assert max(load.values()) - sum(load.values()) / 5 <= widest


def test_shards_split_a_huge_group_and_take_nothing(spark):
    rows = [(i, "same text for all") for i in range(3000)] + [(-i, f"text {i}") for i in range(1, 300)]
    load = collections.Counter()
    for r in sharding.shards_by_bytes(spark.createDataFrame(rows, "doc_id long, text string"), 40).collect():
        load[r.shard] += r.size
    assert len(load) == 40 and max(load.values()) < 1.03 * min(load.values())
    assert sharding.shards_by_bytes(spark.createDataFrame([], "doc_id long, text string")).count() == 0
