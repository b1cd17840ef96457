"""Operators against brute force on a small fixture with hard cases."""

import random
import struct
import zlib
from collections import Counter, defaultdict
from itertools import product

import numpy as np
import pytest
from compare import SMALL
from tokenizers import Tokenizer
from xxhash import xxh64_intdigest

from avcurate.llm import bpe, bwt, chat, components, embeddings, langid, media, packing, queries, repeats, sharding, simhash, warc, webp


def rows(df, key="doc_id"):
    return {r[key]: r for r in df.collect()}


def sha(b):
    import hashlib

    return hashlib.sha256(b).hexdigest()


def union_find(ids, links):
    root = {i: i for i in ids}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for a, b in links:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


# --- language identification -----------------------------------------------------------------------


def test_languages_are_told_apart(spark):
    from pyspark.sql import functions as F

    found = queries.op1_langid(spark, SMALL).join(spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "lang"), "doc_id")
    hit = found.where("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0]
    assert hit > 0.97
    assert found.where("score < 0 or score > 1 or score is null").count() == 0


def test_spans_of_mixed_text():
    counts = [("word", "de", w, 50) for w in ("und", "der", "nicht", "haus")] + [("word", "en", w, 50) for w in ("the", "and", "house", "with")]
    counts += [("word", "ru", w, 50) for w in ("дом", "это")]
    counts += [("total", lang, "word", 200) for lang in ("de", "en", "ru")] + [("total", lang, "gram", 500) for lang in ("de", "en", "ru")]
    counts += [("script", "de", "latin", 200), ("script", "en", "latin", 200), ("script", "ru", "cyrillic", 100)]
    s = langid.Scorer(langid.Model(counts))
    (lang, score, spans), und, digits = langid.label(["und der nicht haus the and house with the and house with the", None, "12 ²"], s, 8.0)
    assert lang == "en" and [x[0] for x in spans] == ["de", "en"] and spans[1][1] == 4 and 0.5 < score < 1
    assert und[:2] == ("und", 0.0) and digits[:2] == ("und", 0.0)
    assert langid.label(["дом это дом"], s, 8.0)[0][:2] == ("ru", 1.0)


def test_unspaced_runs_are_read_whole():
    """Runs of letters are words of one script and of a bounded length, which cover them."""
    rng = random.Random(3)
    for _ in range(200):
        run = "".join("".join(rng.choices(a, k=rng.randint(1, 150))) for a in rng.choices(["abcé", "дом", "漢字", "かな", "αβ"], k=4))
        found = langid.find_words(f"1 {run}_x")
        assert "".join(found) == run + "x" and max(map(len, found)) <= 64
        assert all(len({langid.script_of(c) for c in w}) == 1 for w in found)
    counts = [("gram", lang, w[i : i + 3], 50) for lang, w in (("de", "undder"), ("en", "thehouse")) for i in range(len(w) - 2)]
    counts += [("word", "ru", "дом", 50), ("word", "en", "x", 1), ("word", "de", "y", 1)]
    counts += [("total", lang, kind, 200) for lang in ("de", "en", "ru") for kind in ("word", "gram")]
    counts += [("script", "de", "latin", 200), ("script", "en", "latin", 200), ("script", "ru", "cyrillic", 100)]
    s = langid.Scorer(langid.Model(counts))
    long, mixed = langid.label(["undder" * 11 + "thehouse" * 60, "undder" + "дом" * 40], s, 2.0)
    assert long[0] == "en" and [x[0] for x in long[2]] == ["de", "en"]
    assert mixed[0] == "ru" and [x[0] for x in mixed[2]] == ["de", "ru"]


def test_labels_against_all_paths():
    """Counts, scores, paths and shares made here plainly, with every path of labels tried."""
    rng = random.Random(17)
    langs, penalty, clip = ["aa", "bb", "cc"], 3.0, 6.0
    alphabet = {"aa": "abcde", "bb": "cdefg", "cc": "efgab"}
    word = lambda lang: "".join(rng.choices(alphabet[lang], k=rng.randint(1, 5)))
    train = [(lang, [word(lang) for _ in range(60)]) for lang in langs for _ in range(3)]
    count, total = defaultdict(lambda: dict.fromkeys(langs, 0)), {k: dict.fromkeys(langs, 0) for k in ("word", "gram")}
    for lang, ws in train:
        for w in ws:
            count["word", w][lang] += 1
            total["word"][lang] += 1
            for g in langid.grams_of(w):
                count["gram", g][lang] += 1
                total["gram"][lang] += 1
            count["script", "latin"][lang] += 1
    rows_ = [(kind, lang, item, n) for (kind, item), by in count.items() for lang, n in by.items() if n]
    rows_ += [("total", lang, kind, n) for kind in total for lang, n in total[kind].items()]
    size = {k: sum(kind == k for kind, _ in count) + 1 for k in ("word", "gram")}
    log = lambda kind, item, lang: np.log((count[kind, item][lang] + 0.5 if (kind, item) in count else 0.5) / (total[kind][lang] + 0.5 * size[kind]))

    def score(w):
        own = [log("word", w, k) if ("word", w) in count else sum(log("gram", g, k) for g in langid.grams_of(w)) for k in langs]
        return [max(x - max(own), -clip) for x in own]

    s = langid.Scorer(langid.Model(rows_))
    for _ in range(60):
        ws = [word(rng.choice(langs)) for _ in range(rng.randint(1, 6))]
        table = [score(w) for w in ws]
        best = max(product(range(3), repeat=len(ws)), key=lambda p: (round(sum(t[k] for t, k in zip(table, p)) - penalty * sum(x != y for x, y in zip(p, p[1:])), 6)))
        value = lambda p: sum(t[k] for t, k in zip(table, p)) - penalty * sum(x != y for x, y in zip(p, p[1:]))  # noqa: B023, E731
        lang, share, spans = langid.label([" ".join(ws)], s, penalty)[0]
        path = [langs.index(k) for k, _, n in spans for _ in range(n)]
        assert abs(value(path) - value(best)) < 1e-3
        weight = [sum(len(w) for w, t, k in zip(ws, table, path) if k == i and any(t)) for i in range(3)]
        if any(weight):
            assert lang == langs[weight.index(max(weight))] and abs(share - max(weight) / sum(map(len, ws))) < 1e-9


def test_certain_paths_are_best_paths():
    rng = np.random.default_rng(1)
    for _ in range(300):
        sc = (rng.normal(size=(20, 3)) * rng.choice([0.5, 2, 5]) + [rng.choice([0, 2]), 0, 0]).astype(np.float32)
        x = rng.integers(0, 20, rng.integers(1, 40)).astype(np.int32)
        value = lambda p: sc[x, p].sum() - 8 * (np.diff(p.astype(int)) != 0).sum()  # noqa: E731, B023
        best = langid.viterbi([x], sc, 8.0)[0]
        if (at := langid.stays(sc[x], 8.0)) is not None:
            assert value(np.full(len(x), at)) >= value(best) - 1e-3


def test_language_edges(docs, empty_docs):
    got = rows(langid.identify_documents(docs))
    assert len(got) == docs.count()
    assert langid.identify_documents(empty_docs).count() == 0
    kept = langid.keep_identified(docs)
    assert kept.columns == docs.columns and kept.where("text is null").count() == 0


# --- embeddings ----------------------------------------------------------------------------------------


@pytest.mark.parametrize("crowd", [4096, 3])
def test_embedding_links(spark, crowd):
    rng = np.random.default_rng(3)
    base = rng.normal(size=(40, 8))
    v = [x.tolist() for x in np.vstack([base, base[:10] + 0.1 * rng.normal(size=(10, 8)), base[:5], base[7:8] * 3, base[8:9] + 0.2 * rng.normal(size=(1, 8))])]
    v += [None, [0.0] * 8, [float("nan")] * 8, [None] * 8, [], [1.0, 2.0], [1.0, 2.0]]
    df = spark.createDataFrame(list(enumerate(v)), "vec_id long, embedding array<float>").repartition(3)
    good = {i: np.array(x, dtype=np.float32).astype(np.float64) for i, x in enumerate(v) if x and None not in x and np.isfinite(x).all() and np.any(x)}
    links = [(i, j) for i in good for j in good if i < j and len(good[i]) == len(good[j]) and good[i] @ good[j] / np.sqrt((good[i] @ good[i]) * (good[j] @ good[j])) >= 0.95]
    degree = Counter(x for p in links for x in p)
    comp = union_find(range(len(v)), links)
    got = rows(embeddings.near_duplicates(df, bucket=4, crowd=crowd), "vec_id")
    for i in range(len(v)):
        assert (got[i].n_links, got[i].component_id, got[i].kept) == (degree[i], comp[i], comp[i] == i)
    assert embeddings.near_duplicates(df.where("false")).count() == 0


def test_embedding_tables_reach_the_miss_bound():
    for n in (10, 5_000, 1_000_000):
        bits, tables = embeddings.plan_tables(n, 0.95)
        hit = (1 - np.arccos(0.95) / np.pi) ** bits
        assert (1 - hit) ** tables <= 1e-6


def test_planted_links_are_found(spark):
    """Pairs planted next to the threshold among vectors of their own, null and repeated ids, and columns of names that are used inside."""
    rng = np.random.default_rng(8)
    base = rng.normal(size=(1500, 32))
    base /= np.linalg.norm(base, axis=1, keepdims=True)
    turn = rng.normal(size=base.shape)
    turn -= (turn * base).sum(axis=1, keepdims=True) * base
    turn /= np.linalg.norm(turn, axis=1, keepdims=True)
    cosine = rng.uniform(0.93, 0.97, (len(base), 1))
    v = np.vstack([base, cosine * base + np.sqrt(1 - cosine**2) * turn])
    df = spark.createDataFrame([(i, x, 7, "k") for i, x in enumerate(v.tolist())] + [(None, v[0].tolist(), 7, "k")], "vec_id long, embedding array<double>, n long, key string").repartition(3)
    unit = v / np.sqrt((v * v).sum(axis=1))[:, None]
    i, j = np.nonzero(np.triu(unit @ unit.T >= 0.95, 1))
    degree, comp = Counter([*i.tolist(), *j.tolist()]), union_find(range(len(v)), zip(i.tolist(), j.tolist()))
    got = embeddings.near_duplicates(df).collect()
    assert len(got) == len(v) + 1 and len(i) > 500
    assert {r.vec_id: (r.n_links, r.component_id) for r in got if r.vec_id is not None} == {k: (degree[k], comp[k]) for k in range(len(v))}
    assert [(r.n_links, r.kept) for r in got if r.vec_id is None] == [(0, True)]


def test_components_of_a_chain_and_a_star(spark):
    edges = [(i, i + 1) for i in range(0, 60)] + [(100, 100 + i) for i in range(1, 40)] + [(7, 7), (200, None)]
    df = spark.createDataFrame(edges, "u long, v long")
    got = {r.id: r.component for r in components.connected_components(df).collect()}
    assert {got[i] for i in range(61)} == {0} and {got[i] for i in range(100, 140)} == {100} and 200 not in got
    assert components.connected_components(df.where("false")).count() == 0


# --- simhash -----------------------------------------------------------------------------------------------


def brute_fingerprint(text, k):
    w = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").encode()
    w = [x for x in w.replace(b"\t", b" ").replace(b"\n", b" ").replace(b"\r", b" ").replace(b"\x0b", b" ").replace(b"\x0c", b" ").split(b" ") if x]
    grams = [b" ".join(w[i : i + k]) for i in range(len(w) - k + 1)] if len(w) >= k else [b" ".join(w)] if w else []
    h = [xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


@pytest.mark.parametrize("k", [3, 5])
def test_simhash(docs, texts, empty_docs, k):
    fp = {10 * i + 3: brute_fingerprint(t, k) for i, t in enumerate(texts)}
    ids = list(fp)
    comp = union_find(ids, [(a, b) for a in ids for b in ids if a < b and (fp[a] ^ fp[b]).bit_count() <= 3])
    got = rows(simhash.near_duplicates(docs, k))
    assert {i: (got[i].fingerprint, got[i].component_id) for i in ids} == {i: (f"{fp[i]:016x}", comp[i]) for i in ids}
    assert simhash.near_duplicates(empty_docs).count() == 0


def test_similar_documents(docs, texts, empty_docs):
    """All pairs at the bound or above, by whole sets, are linked; nothing else but fingerprints within three bits."""
    rng = random.Random(12)
    more = []
    for n in (30, 60, 120):
        w = ["".join(rng.choices("abcdefg", k=5)) for _ in range(n)]
        more.append(" ".join(w))
        for cut in (1, 2):
            x = list(w)
            for _ in range(cut):
                x[rng.randrange(n)] = "zzz"
            more.append(" ".join(x))
    all_ = texts + more
    df = docs.select("doc_id", "text").unionByName(docs.sparkSession.createDataFrame([(10_000 + i, t) for i, t in enumerate(more)], "doc_id long, text string"))
    ids = [10 * i + 3 for i in range(len(texts))] + [10_000 + i for i in range(len(more))]
    fp = {i: brute_fingerprint(t, 5) for i, t in zip(ids, all_)}
    sets = {i: set(simhash.shingles(t or "", 5)) for i, t in zip(ids, all_)}
    like = lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]) if sets[a] | sets[b] else True
    comp = union_find(ids, [(a, b) for a in ids for b in ids if a < b and (like(a, b) or (fp[a] ^ fp[b]).bit_count() <= 3)])
    got = {r.doc_id: r.component_id for r in simhash.similar_documents(df).collect()}
    assert got == comp
    assert {r.doc_id for r in simhash.keep_one(df).collect()} == {i for i in ids if comp[i] == i}
    assert simhash.keep_one(empty_docs).count() == 0 and simhash.keep_one(docs).columns == docs.columns


@pytest.mark.parametrize("group", [512, 3])
def test_similar_texts_above_a_sketch(spark, monkeypatch, group):
    """Texts of 130 to 900 shingles, next to the bound: those at it or above are linked, others are not."""
    monkeypatch.setattr(simhash, "GROUP", group, raising=False)
    rng = random.Random(80)
    texts = []
    for n in [135, 160, 300, 500, 900] * 12:
        w = ["".join(rng.choices("abcdefghij", k=6)) for _ in range(n)]
        cut = round(n * rng.uniform(0.08, 0.14))
        at = rng.randrange(n - cut)
        texts += [" ".join(w), " ".join(w[:at] + ["".join(rng.choices("abcdefghij", k=6)) for _ in range(cut)] + w[at + cut :])]
    texts += [" ".join(texts[6].split()[:i] + [f"new{i}"] + texts[6].split()[i:]) for i in range(10, 100, 15)]
    sets = [set(simhash.shingles(t, 5)) for t in texts]
    fp = [brute_fingerprint(t, 5) for t in texts]
    near = [(a, b) for b in range(len(texts)) for a in range(b) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]) or (fp[a] ^ fp[b]).bit_count() <= 3]
    assert 20 < len(near) and min(map(len, sets)) > simhash.SKETCH
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    assert {r.doc_id: r.component_id for r in simhash.similar_documents(df).collect()} == union_find(range(len(texts)), near)


@pytest.mark.parametrize("limit", [0, 1, 3, 6, 9])
def test_simhash_links_all_near_fingerprints(spark, limit):
    rng = random.Random(5)
    fps = []
    for _ in range(40):
        f = rng.getrandbits(64)
        fps.append(f)
        for bits in (1, 2, 3, 3, 4, max(1, limit - 1), limit or 1, limit + 1):
            g = f
            for b in rng.sample(range(64), bits):
                g ^= 1 << b
            fps.append(g)
    fps = sorted(set(fps))
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    df = spark.createDataFrame([(i, f) for i, f in enumerate(signed)], "doc_id long, fp long")
    comp = union_find(range(len(fps)), [(a, b) for a in range(len(fps)) for b in range(a) if (fps[a] ^ fps[b]).bit_count() <= limit])
    got = {r.doc_id: r.component_id for r in simhash.fingerprint_components(df, limit).collect()}
    assert got == comp
    with pytest.raises(ValueError):
        simhash.fingerprint_components(df, 64)


# --- media ---------------------------------------------------------------------------------------------------


def test_media(docs, texts, empty_docs):
    got = rows(media.read_media(media.store_texts(docs), samples=True))
    for i, t in enumerate(texts):
        raw = (t or "").encode()
        p = raw + b" " * (max(192, -(-len(raw) // 192) * 192) - len(raw))
        r = got[10 * i + 3]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32, bytes(r.samples)) == (len(raw), len(p), sha(p), zlib.crc32(p[-16:]), p)
    assert media.read_media(media.store_texts(empty_docs)).count() == 0


class Writer(webp.BitWriter):
    """Writes images with features that the library's own encoder doesn't use."""

    def simple(self, *symbols):
        self.put(1, 1)
        self.put(len(symbols) - 1, 1)
        self.put(1, 1)
        for s in symbols:
            self.put(s, 8)

    def normal(self, lengths):
        """Code lengths spelt out with a flat code of 4 bits for the lengths 0 to 15."""
        self.put(0, 1)
        self.put(15, 4)
        for s in webp.CODE_LENGTH_ORDER:
            self.put(4 if s < 16 else 0, 3)
        self.put(0, 1)
        for n in lengths:
            self.put(int(f"{n:04b}"[::-1], 2), 4)

    def symbol(self, lengths, s):
        used = sorted((n, x) for x, n in enumerate(lengths) if n)
        code = before = 0
        for n, x in used:
            code <<= n - before
            if x == s:
                self.put(int(f"{code:0{n}b}"[::-1], 2), n)
                return
            code, before = code + 1, n
        raise AssertionError(s)

    def file(self):
        data = self.value.to_bytes(self.n // 8 + 1, "little")
        body = b"WEBPVP8L" + struct.pack("<I", len(data)) + data + b"\0" * (len(data) & 1)
        return b"RIFF" + struct.pack("<I", len(body)) + body

    def head(self, w, h):
        self.put(0x2F, 8)
        self.put(w - 1, 14)
        self.put(h - 1, 14)
        self.put(0, 4)


def test_back_references_and_cache():
    w = Writer()
    w.head(8, 2)
    w.put(0, 1)  # no transform
    w.put(1, 1)
    w.put(6, 4)  # cache of 64
    w.put(0, 1)  # one group
    green = [0] * (256 + 24 + 64)
    green[5], green[9] = 2, 2
    key, other = ((webp.CACHE_MULTIPLIER * p & 0xFFFFFFFF) >> 26 for p in (0xFF010502, 0xFF010902))
    assert key != other
    green[256 + 3] = 2
    green[280 + key] = 2
    w.normal(green)
    w.simple(1)
    w.simple(2)
    w.simple(255)
    w.simple(1)  # distance code 1 is the second of the nearby pixels
    w.symbol(green, 5)
    w.symbol(green, 9)
    w.symbol(green, 280 + key)  # the first pixel again, from the cache
    for _ in range(5):
        w.symbol(green, 9)
    w.symbol(green, 256 + 3)  # four pixels back by one column
    w.symbol(green, 256 + 3)
    px = webp.decode(w.file())
    a, b = 0xFF010502, 0xFF010902
    want = [a, b, a, b, b, b, b, b]
    dx, dy = webp.near_offsets()[1]
    for _ in range(8):
        want.append(want[-max(1, dx + dy * 8)])
    assert px.ravel().tolist() == want


def test_transforms():
    rng = np.random.default_rng(2)
    px = rng.integers(0, 1 << 32, (6, 5), dtype=np.uint64).astype(np.uint32)
    for mode in range(14):
        modes = np.full((2, 2), mode << 8, np.uint32)
        out = webp.undo_predictor(px, modes, 2)
        back = []  # the differences that lead there
        for y in range(6):
            for x in range(5):
                if not y:
                    g = int(out[0, x - 1]) if x else webp.BLACK
                elif not x:
                    g = int(out[y - 1, 0])
                else:
                    tr = int(out.ravel()[(y - 1) * 5 + x + 1])
                    g = webp.predict(mode, int(out[y, x - 1]), int(out[y - 1, x]), int(out[y - 1, x - 1]), tr)
                back.append(sum(((int(out[y, x]) >> s & 255) - (g >> s & 255) & 255) << s for s in (0, 8, 16, 24)))
        assert back == px.ravel().tolist()
    green = webp.undo_subtract_green(np.array([[0xFF102030]], np.uint32))
    assert green[0, 0] == 0xFF302050
    cross = webp.undo_cross_colour(np.array([[0x00002000]], np.uint32), np.array([[0x00000020]], np.uint32), 2)
    assert cross[0, 0] == 0x00202000
    assert webp.undo_palette(np.array([[0xE4 << 8]], np.uint32), np.array([1, 2, 3, 4], np.uint32), 4).tolist() == [[1, 2, 3, 4]]
    assert webp.predict(11, 0x10, 0x20, 0x11, 0) == 0x20
    assert [webp.near_offsets()[i] for i in (0, 1, 2, 3, 119)] == [(0, 1), (1, 0), (1, 1), (-1, 1), (8, 7)]


def test_bad_media_is_told():
    good = webp.encode_payload(b"abc " * 48)
    for bad in (good[:-20], b"RIFX" + good[4:], good[:20] + b"\0" + good[21:]):
        with pytest.raises(ValueError):
            webp.decode_payload(bad)


# --- repeats -------------------------------------------------------------------------------------------------


def brute_repeats(texts, length):
    count = Counter(t[i : i + length] for t in texts for i in range(len(t) - length + 1))
    out = []
    for t in texts:
        gone = bytearray(len(t))
        for i in range(len(t) - length + 1):
            if count[t[i : i + length]] > 1:
                gone[i : i + length] = b"\1" * length
        out.append(gone)
    return out


@pytest.mark.parametrize("length, options", [(400, {}), (40, {"gram": 16}), (33, {"gram": 32}), (25, {})])
def test_repeats(docs, texts, empty_docs, length, options):
    raw = [(t or "").encode() for t in texts]
    got = rows(repeats.repeats(docs, length, **options))
    for i, (t, gone) in enumerate(zip(raw, brute_repeats(raw, length))):
        kept = bytes(b for b, g in zip(t, gone) if not g)
        spans = sum(1 for j, g in enumerate(gone) if g and (not j or not gone[j - 1]))
        r = got[10 * i + 3]
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == (len(t), sum(gone), spans, sha(kept))
    assert repeats.repeats(empty_docs, **options).count() == 0


def test_merged_transforms_find_equal_windows():
    """Rows of several keys, with anchors anywhere in them: windows that are equal at equal places from the anchor."""
    for seed in range(300):
        rng = random.Random(seed)
        length = rng.choice([4, 6, 9])
        keys, units, at = [], [], []
        for _ in range(rng.randint(1, 30)):
            at.append(rng.randint(0, length - 1))
            keys.append(rng.randint(0, 1))
            units.append(np.array([rng.choice([0, 1]) if rng.random() < 0.3 else 0 for _ in range(rng.randint(1, at[-1] + 1) + length - 1)], np.uint8))
        windows = [[(k, a - j, bytes(u[j : j + length])) for j in range(len(u) - length + 1)] for k, u, a in zip(keys, units, at)]
        count = Counter(w for some in windows for w in some)
        got = bwt.merge(np.array(keys), units, np.array(at), length)
        assert [m.tolist() for m in got] == [[count[w] > 1 for w in some] for some in windows]
    assert bwt.merge(np.empty(0, np.int64), [], np.empty(0, np.int64), 4) == []


def test_refinement_gives_the_common_prefixes():
    rng = random.Random(6)
    rows_ = ["".join(rng.choices("ab", k=rng.randint(1, 12))).encode() for _ in range(60)]
    flat, size = np.frombuffer(b"".join(rows_), np.uint8), np.array([len(r) for r in rows_])
    order, common = bwt.refine(np.arange(60), np.arange(60) == 0, flat, np.cumsum(size) - size, size, 12)
    found = [rows_[i] for i in order]
    assert found == sorted(found)
    for a, b, n in zip(found, found[1:], common[1:]):
        assert n == next((k for k, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))


@pytest.mark.parametrize("group, block", [(3, 5), (1, 16), (4, 1)])
def test_crowded_anchors_are_split(spark, monkeypatch, group, block):
    """A passage in many unlike contexts, and copies of it with edits: every split gives the same bytes."""
    monkeypatch.setattr(repeats, "GROUP", group)
    monkeypatch.setattr(repeats, "BLOCK", block)
    rng = random.Random(group)
    text = lambda n: "".join(rng.choices("abcde ", k=n))
    passage, texts = text(90), []
    for i in range(60):
        body = passage if i % 3 else passage[: 20 + i] + "-" + passage[21 + i :]
        texts.append(text(i % 7 * 9) + body + text(i % 5 * 20))
    texts += [texts[3], texts[4], texts[4]]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    got = rows(repeats.repeats(df, 40, words=12, gram=16))
    raw = [t.encode() for t in texts]
    for i, (t, gone) in enumerate(zip(raw, brute_repeats(raw, 40))):
        assert (i, got[i].n_removed, got[i].kept_sha256) == (i, sum(gone), sha(bytes(b for b, g in zip(t, gone) if not g)))
    words_ = [t.split() for t in raw]
    count = Counter(tuple(w[j : j + 12]) for w in words_ for j in range(len(w) - 11))
    assert all(count[tuple(w[j : j + 12])] == 1 for t in got.values() for w in [t.text.encode().split()] for j in range(len(w) - 11) if tuple(w[j : j + 12]) in count)


def test_repeats_of_repeated_ids(spark):
    t = "".join(random.Random(1).choices("abcdefgh", k=900))
    df = spark.createDataFrame([(1, t), (1, t), (1, "x" * 500), (None, t[:450]), (2, None)], "doc_id long, text string")
    got = sorted((r.doc_id or 0, r.n_bytes, r.n_removed) for r in repeats.repeats(df).collect())
    assert got == [(0, 450, 450), (1, 500, 500), (1, 900, 900), (1, 900, 900), (2, 0, 0)]


@pytest.mark.parametrize("parts", [1, 2, 5])
def test_repeats_of_copies_next_to_near_copies(spark, parts):
    """Exact copies in one batch or in several, copies with one edit, and texts that repeat themselves."""
    texts = []
    for seed in range(24):
        rng = random.Random(seed)
        t = "".join(rng.choices("abcdefgh", k=900))
        at = rng.randrange(900)
        edited = t[:at] + "-" + t[at + 1 :]
        texts += [[t, t, edited], [t + "." + t, edited], [edited, t, "x" + t, t[100:]]][seed % 3]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    df = df.coalesce(1) if parts == 1 else df.repartition(parts)
    got = rows(repeats.repeats(df))
    raw = [t.encode() for t in texts]
    for i, (t, gone) in enumerate(zip(raw, brute_repeats(raw, 400))):
        assert (i, got[i].n_removed, got[i].kept_sha256) == (i, sum(gone), sha(bytes(b for b, g in zip(t, gone) if not g)))


def test_remove_repeats_keeps_rows_and_columns(docs, texts):
    out = repeats.remove_repeats(docs)
    assert out.columns == docs.columns and out.count() == len(texts)
    got = rows(out)
    gone = brute_repeats([(t or "").encode() for t in texts], 400)
    for i, t in enumerate(texts):
        left = bytes(b for b, g in zip((t or "").encode(), gone[i]) if not g).decode("utf-8", "ignore")
        assert got[10 * i + 3].text == (None if t is None else left)


def test_remove_repeats_deals_texts_once(spark):
    """What is left of a text has its row's columns of any type already: nothing is joined to them after that."""
    t = "".join(random.Random(2).choices("abcdefgh", k=900))
    df = spark.createDataFrame([(1, t, 900), (2, t[:450] + "é", 451), (3, None, None), (4, "x", 7)], "doc_id long, text string, n_chars int").selectExpr(
        "*", "array(named_struct('a', doc_id, 'b', map('k', text))) AS nested", "timestamp'2024-01-01 00:00:00' AS at", "1.50BD AS price", "binary(text) AS rid", "doc_id * 9007199254740993 AS z", "CAST(NULL AS long) AS first",
    )
    out = repeats.remove_repeats(df)
    assert "Join" not in out._jdf.queryExecution().optimizedPlan().toString().split("MapInArrow")[0]
    got, own = rows(out), rows(df)
    assert {i: (r.text, r.n_chars) for i, r in got.items()} == {1: (t[450:], 450), 2: ("é", 1), 3: (None, None), 4: ("x", 7)}
    assert all(r[3:] == own[i][3:] for i, r in got.items()) and out.columns == df.columns


@pytest.mark.parametrize("parts", [1, 4])
def test_pipeline_removes_passages_of_more_than_50_words(spark, parts):
    """Passages of 51 to 65 words go from all texts, of any word length and white space between; those of 50 stay."""
    import corpus_pipeline

    rng = random.Random(51)
    word = lambda least, most: "".join(rng.choices("abcdefghijk", k=rng.randint(least, most)))
    texts, long = [], "".join(rng.choices("abcdefgh", k=450))
    for n in [*range(48, 66), 51, 52, 130]:
        passage = [word(*rng.choice([(1, 2), (4, 7)])) for _ in range(n)]
        for sep in (" ", "\n", "  "):
            texts.append(" ".join(word(9, 12) for _ in range(rng.randint(0, 90))) + sep + sep.join(passage) + " " + " ".join(word(9, 12) for _ in range(20)))
    texts += [f"one {long} two", f"three {long} four", texts[0], None, " ", "x"]
    words = [[x.encode() for x in (t or "").split()] for t in texts]
    count = Counter(tuple(w[i : i + 51]) for w in words for i in range(len(w) - 50))
    by_bytes = brute_repeats([(t or "").encode() for t in texts], 400)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = rows(corpus_pipeline.remove_repeated_passages(spark, df.coalesce(1) if parts == 1 else df.repartition(parts), SMALL))
    for i, (t, w) in enumerate(zip(texts, words)):
        gone, ends, at = by_bytes[i], [], 0
        for x in w:
            at = t.index(x.decode(), at) + len(x)
            ends.append(at)
        for j in range(len(w) - 50):
            if count[tuple(w[j : j + 51])] > 1:
                lo = ends[j] - len(w[j])
                gone[lo : ends[j + 50]] = b"\1" * (ends[j + 50] - lo)
        assert got[i].text == (None if t is None else "".join(c for c, g in zip(t, gone) if not g)), i
    assert got[7].text.count("\n") == 50 and got[10].text.count("\n") == 1  # 50 words stay; 51 go, but for the white space around


# --- packing ---------------------------------------------------------------------------------------------------


def test_first_fit_decreasing_is_what_it_says():
    rng = random.Random(3)
    for _ in range(50):
        sizes = [rng.randint(1, 50) for _ in range(rng.randint(1, 60))]
        got = packing.first_fit_decreasing(sizes, 50)
        room, want = [], [None] * len(sizes)
        for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
            b = next((b for b, r in enumerate(room) if r >= sizes[i]), None)
            if b is None:
                room.append(50)
                b = len(room) - 1
            want[i] = (b, 50 - room[b])
            room[b] -= sizes[i]
        assert got == want


def test_packing(docs, texts, empty_docs, tokenizer):
    path = tokenizer("byte_bpe_50k.json")
    tok = Tokenizer.from_file(path)
    out = packing.pack_documents(docs, path, length=64, group_rows=10).collect()
    pieces, seqs = defaultdict(list), defaultdict(list)
    for r in out:
        pieces[r.doc_id].append(r)
        seqs[r.sequence_id].append((r.offset, r.length))
    for i, t in enumerate(texts):
        ids = tok.encode(t or "", add_special_tokens=False).ids + [1]
        mine = sorted(pieces[10 * i + 3], key=lambda r: r.start)
        at = 0
        for r in mine:
            assert r.start == at and r.doc_tokens == len(ids)
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids)
    for s in seqs.values():
        at = 0
        for offset, n in sorted(s):
            assert offset == at
            at += n
        assert at <= 64
    assert packing.pack_documents(empty_docs, path).count() == 0


# --- WARC ----------------------------------------------------------------------------------------------------------


def pages(spark):
    rng = random.Random(8)
    body = "<html>" + "".join(rng.choices("abc <>/é", k=500)) + "</html>"
    rows_ = [(5, "u5", body), (2, "u 2", body), (9, None, body), (3, "u3", "short"), (4, "u4", "short"), (6, "u6", None), (7, "u7", ""), (8, "u8", "é" * 50), (1, "u1", "é" * 50), (None, "n", "z" * 200)]
    return rows_, spark.createDataFrame([(*r, 1) for r in rows_], "page_id long, url string, html string, payload_digest int").repartition(3)


def test_warc(spark):
    rows_, df = pages(spark)
    got = rows(warc.read_archives(warc.archive_pages(df), payloads=True), "page_id")
    assert len(got) == len(rows_)
    for pid, _, html in rows_:
        p = (html or "").encode()
        same = [x for x, _, h in rows_ if (h or "").encode() == p and x is not None]
        first = min(same) if len(p) >= 100 and same else pid
        r = got[pid]
        assert (r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) == (len(p), sha(p), "response" if first == pid else "revisit", None if first == pid else first)
        assert bytes(r.payload) == (p if first == pid else b"")
    assert warc.read_archives(warc.archive_pages(df.where("false"))).count() == 0


def test_warc_validates():
    import zstandard as zstd

    p = b"x" * 300
    raw = warc.record(1, "u", p, sha(p), "response", None)
    assert warc.parse_record(raw)[:4] == (1, 300, sha(p), "response")
    for bad in (raw[:-1], raw.replace(b"WARC/1.1", b"WARX/1.1"), raw.replace(b"WARC-Date", b"WARC-Dat"), raw.replace(b"xxx", b"xyx", 1), raw + b" "):
        with pytest.raises((ValueError, KeyError)):
            warc.parse_record(bad)
    d = b"some words that repeat some words"
    z = zstd.ZstdCompressor(dict_data=zstd.ZstdCompressionDict(d))
    archive = warc.dictionary_frame(zstd.ZstdCompressor().compress(d)) + z.compress(raw) + z.compress(raw)
    assert list(warc.frames(archive)) == [raw, raw]
    with pytest.raises(ValueError):
        list(warc.frames(archive[:-5]))
    assert list(warc.frames(zstd.ZstdCompressor().compress(raw))) == [raw]


# --- sharding -------------------------------------------------------------------------------------------------------


def test_sharding(docs, texts, empty_docs):
    out = sharding.shard_documents(docs, 5, bucket_rows=4).collect()
    got = {r.doc_id: r for r in out}
    more = {r.doc_id: r for r in sharding.shard_documents(docs, 6, bucket_rows=1000).collect()}
    slots = defaultdict(list)
    for i, t in enumerate(texts):
        r = got[10 * i + 3]
        raw = (t or "").encode()
        assert (r.size, r.text_crc32, r.law) == (len(raw) + 8, zlib.crc32(raw), "key") and 0 <= r.shard < 5
        assert r.grown_shard in (r.shard, 5) and more[10 * i + 3].shard == r.grown_shard
        slots[r.shard].append(r.slot)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert sorted(map(tuple, out)) == sorted(map(tuple, sharding.shard_documents(docs, 5, bucket_rows=4).collect()))
    assert sharding.shard_documents(empty_docs).count() == 0
    twice = docs.unionByName(docs)
    assert sharding.shard_documents(twice, 5).count() == 2 * len(texts)


def test_shards_are_written_in_order(spark, docs, tmp_path):
    some = docs.select("doc_id", "text")
    sharding.write_shards(some, f"file://{tmp_path}/s", 3, 8)
    assert spark.read.parquet(f"file://{tmp_path}/s").count() == docs.count()


def test_sharding_writes_the_texts_and_reads_them_back(spark, monkeypatch):
    """Null and repeated ids keep all their rows; what is told of a shard is what was written."""
    paths, write = [], sharding.write_shards
    monkeypatch.setattr(sharding, "write_shards", lambda docs, path, *a: (paths.append(path), write(docs, path, *a)))
    texts = [(i % 7 or None, None if i % 11 == 3 else f"text {i}") for i in range(60)] + [(1, "text 1")]
    df = spark.createDataFrame(texts, "doc_id long, text string").repartition(3)
    got = sharding.shard_documents(df, 3, bucket_rows=4).collect()
    written = spark.read.parquet(paths[0]).collect()
    order = lambda x: sorted(x, key=repr)
    assert order((r.doc_id, r.text) for r in written) == order(texts)
    assert order((r.shard, r.slot, r.doc_id, len((r.text or "").encode()) + 8, zlib.crc32((r.text or "").encode())) for r in written) == order((r.shard, r.slot, r.doc_id, r.size, r.text_crc32) for r in got)
    for shard in range(3):
        slots = [r.slot for r in got if r.shard == shard]
        assert sorted(slots) == list(range(len(slots)))


# --- BPE ---------------------------------------------------------------------------------------------------------------


def test_bpe(docs, texts, empty_docs, tokenizer):
    path = tokenizer("word_bpe_49k.json")
    tok = Tokenizer.from_file(path)
    tok.no_truncation()
    tok.no_padding()
    got = rows(bpe.encode_documents(docs, path, with_ids=True))
    for i, t in enumerate(texts):
        ids = tok.encode(t or "", add_special_tokens=False).ids
        text = tok.decode(ids, skip_special_tokens=False)
        r = got[10 * i + 3]
        assert (r.n_tokens, r.ids, r.decoded) == (len(ids), ids, text)
        assert (r.ids_sha256, r.decoded_sha256) == (sha(" ".join(map(str, ids)).encode()), sha(text.encode()))
    assert bpe.encode_documents(empty_docs, path).count() == 0


def test_cuts_never_split_a_token(tokenizer):
    b = bpe.Bpe(tokenizer("word_bpe_49k.json"))
    assert len(b.cuts("".join(b.chars[x] for x in "qzxq漢字".encode()))) > 1
    for token in list(b.vocab)[::97]:
        assert b.cuts(token.removesuffix(bpe.END)) == [token.removesuffix(bpe.END)]


# --- chat ------------------------------------------------------------------------------------------------------------------


def test_chat_events(spark):
    log = [
        (1, 0, 0, "post", "user", "a</turn>\n<loss>\\l\\b"), (1, 1, 1, "post", "assistant", "He"), (1, 1, 2, "delta", None, "llo"), (1, 1, 3, "delta", None, "!"),
        (1, 2, 4, None, "user", None), (1, 3, 5, "post", "assistant", "old"), (1, 3, 6, "regenerate", "assistant", "new"), (1, 3, 7, "delta", None, " one"), (1, 4, 8, "post", "us<er", "x"), (1, 4, 9, "edit", "user", "y"),
        (None, 0, 0, "post", "assistant", "n"), (2, 0, 0, "post", "user", "b"), (2, 0, 0, "post", "user", "b"), (3, 0, 0, "delta", None, "tail"),
    ]
    df = spark.createDataFrame(log, "conv_id long, message long, seq long, op string, role string, text string").repartition(3)
    got = {r.conv_id: [(t.role, t.text, t.loss) for t in r.turns] for r in chat.parse(chat.render(chat.fold_events(df))).collect()}
    assert got[1] == [("user", "a</turn>\n<loss>\\l\\b", False), ("assistant", "Hello!", True), ("user", "", False), ("assistant", "new one", True), ("user", "y", False)]
    assert got[None] == [("assistant", "n", True)] and got[2] == [("user", "b", False)] * 2 and got[3] == [("", "tail", False)]
    assert chat.render(chat.fold_events(df.where("false"))).count() == 0


def test_chat_runs_keep_the_order(spark):
    df = spark.range(300).selectExpr("7L AS conv_id", "id AS turn", "'user' AS role", "concat('t', id) AS text")
    r = chat.parse(chat.render(chat.fold_events(chat.log_of_turns(df)), chunk=16)).first()
    assert [t.text for t in r.turns] == [f"t{i}" for i in range(300)]


# --- very long texts, odd ids, clashing columns ----------------------------------------------------------------------------


@pytest.fixture(scope="module")
def long_docs(spark):
    """Texts of a million characters and more: white space, words, one repeated line; an id above 2^53 next to a null one."""
    rng = random.Random(23)
    words_ = ["".join(rng.choices("abcdefghij", k=rng.randint(2, 8))) for _ in range(3000)]
    long = " ".join(rng.choices(words_, k=200_000))
    texts_ = {(1 << 53) + 1: " " * 1_200_000 + "x", 5: long, 6: long[:300_000] + "\n" * 5000 + long[300_000:], 7: "one line\n" * 120_000, 8: "short"}
    rows_ = [(i, t, "en", "s", len(t), 1.0, "k", b"z") for i, t in texts_.items()] + [(None, "no id", None, None, None, None, None, None)]
    return {**texts_, None: "no id"}, spark.createDataFrame(rows_, "doc_id long, text string, lang string, source string, n_chars long, rid double, key string, fp binary").repartition(2)


def test_very_long_texts(spark, long_docs, tokenizer):
    texts_, df = long_docs
    raw = {i: t.encode() for i, t in texts_.items()}
    found = rows(langid.identify_documents(df))
    assert set(found) == set(texts_) and all(0 <= r.score <= 1 for r in found.values())
    got = rows(simhash.near_duplicates(df))
    assert set(got) == set(texts_) and got[5].component_id == 5 and got[(1 << 53) + 1].doc_id == (1 << 53) + 1
    assert got[5].fingerprint == f"{simhash.fingerprint(texts_[5]):016x}"
    got = rows(media.read_media(media.store_texts(df)))
    for i, t in raw.items():
        p = t + b" " * (max(192, -(-len(t) // 192) * 192) - len(t))
        assert (got[i].n_bytes, got[i].payload_sha256) == (len(t), sha(p))
    got = rows(repeats.repeats(df))
    assert got[5].n_removed == len(raw[5]) and got[8].n_removed == 0 and got[None].n_bytes == 5
    assert got[7].n_removed == len(raw[7]) and got[(1 << 53) + 1].n_removed == 1_200_000
    assert {i: r.n_bytes for i, r in got.items()} == {i: len(t) for i, t in raw.items()}
    path = tokenizer("byte_bpe_50k.json")
    tok, out = Tokenizer.from_file(path), packing.pack_documents(df, path).collect()
    for i, t in texts_.items():
        assert sum(r.length for r in out if r.doc_id == i) == len(tok.encode(t, add_special_tokens=False).ids) + 1
    path = tokenizer("word_bpe_49k.json")
    tok, got = Tokenizer.from_file(path), rows(bpe.encode_documents(df, path))
    assert all(got[i].n_tokens == len(tok.encode(t, add_special_tokens=False).ids) for i, t in texts_.items())
    got = {r.doc_id: r for r in sharding.shard_documents(df, 3).collect()}
    assert {i: (r.size, r.text_crc32) for i, r in got.items()} == {i: (len(t) + 8, zlib.crc32(t)) for i, t in raw.items()}
    log = spark.createDataFrame([(i, j, "assistant", t) for i, t in texts_.items() for j in range(2)], "conv_id long, turn long, role string, text string")
    got = rows(chat.digests(chat.parse(chat.render(chat.fold_events(chat.log_of_turns(log))))), "conv_id")
    assert all(got[i].loss_sha256 == sha(2 * t) and got[i].n_turns == 2 for i, t in raw.items())
    pages_ = df.selectExpr("doc_id AS page_id", "'u' AS url", "text AS html", "key AS payload_digest")
    got = rows(warc.checked(warc.read_archives(warc.archive_pages(pages_))), "page_id")
    assert {i: (r.payload_bytes, r.payload_digest) for i, r in got.items()} == {i: (len(t), sha(t)) for i, t in raw.items()}


def test_turns_come_back_from_derived_logs(spark):
    """Posts, streams, edits and regenerations all occur, and fold to the turns, rows of one turn included."""
    turns = [(c, t, ["user", "assistant"][t % 2], None if (c + t) % 11 == 0 else f"text {c} {t} \U0001f600 <l") for c in range(9) for t in range(9)] + [(3, 2, "user", "again"), (3, 2, "user", "again")]
    df = spark.createDataFrame([(*x, "s", 1) for x in turns], "conv_id long, turn long, role string, text string, part string, seq int").repartition(3)
    log = chat.log_of_turns(df)
    assert {r.op for r in log.select("op").distinct().collect()} == {"post", "delta", "edit", "regenerate"}
    got = {r.conv_id: [(t.role, t.text) for t in r.turns] for r in chat.parse(chat.render(chat.fold_events(log))).collect()}
    for c in range(9):
        assert got[c] == [(r, x or "") for _, t, r, x in sorted((x for x in turns if x[0] == c), key=lambda x: (x[1], x[2], x[3] or ""))]


def test_a_revisit_needs_its_response(spark):
    _, df = pages(spark)
    records = warc.read_archives(warc.archive_pages(df))
    assert warc.checked(records).count() == 10
    with pytest.raises(ValueError):
        warc.checked(records.where("not (record_type = 'response' and page_id = 2)"))


def test_long_white_space_is_encoded_as_by_the_library(tokenizer):
    from avcurate.llm import tokens

    ids, rng = tokens.TextIds(tokenizer("byte_bpe_50k.json")), random.Random(2)
    for _ in range(30):
        gaps = [rng.choice([" ", "\n", " \n", "\u3000", "\xa0 "]) * rng.choice([1, 2000, tokens.LONG_GAP - 1, tokens.LONG_GAP, tokens.LONG_GAP + 1]) for _ in range(3)]
        text = rng.choice(["", "a "]) + "".join(g + rng.choice(["x", "é1", "!"]) for g in gaps[:-1]) + gaps[-1] + rng.choice(["", "z"])
        assert ids(text) == ids.tok.encode(text, add_special_tokens=False).ids


def test_images_in_step_equal_images_alone():
    rng = random.Random(4)
    for _ in range(12):
        payloads = []
        for _ in range(rng.randint(1, 8)):
            letters = rng.choice([b"ab", bytes(range(256)), b"etaoin shrdlu.,mnopqrstABC", "дом это язык ж".encode(), b"0123456789abcdef-_."])
            body = bytes(rng.choices(letters, k=rng.randint(1, 4000)))
            body = body[: rng.randint(1, 600)] * rng.randint(1, 12) + body
            payloads.append(body + b" " * (-len(body) % 192))
        stored = webp.encode_payloads(payloads)
        assert webp.decode_payloads(stored) == payloads and [webp.encode_payload(p) for p in payloads] == stored
        for p, m in zip(payloads, stored):
            assert b"".join((webp.decode_vp8l(x) >> np.uint32(8)).astype(np.uint8).tobytes() for x in webp.containers(m)) == p
    with pytest.raises(ValueError):
        webp.encode_payload(b"abc")
    cut = webp.encode_payload(bytes(range(192)) * 8)
    with pytest.raises(ValueError):
        webp.decode_payload(cut[:4] + struct.pack("<I", len(cut) - 208) + cut[8:16] + struct.pack("<I", len(cut) - 220) + cut[20:-200])


def test_near_copies_of_repeated_and_null_ids(spark):
    t = " ".join(f"word{i}" for i in range(60))
    df = spark.createDataFrame([(7, t, 1), (7, t, 2), (None, t, 3), (7, "another text", 4), (2, "third", 5), (None, "fourth one", 6)], "doc_id long, text string, rid int")
    kept_ = sorted((r.doc_id or 0, r.text) for r in simhash.keep_one(df).collect())
    assert kept_ == sorted([(7, t), (7, "another text"), (2, "third"), (0, "fourth one")])
    assert simhash.keep_one(df).columns == df.columns
