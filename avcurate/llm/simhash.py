"""SimHash near-duplicates with pigeonring filtering.

A fingerprint has 64 bits in a ring of t + 1 segments, where links differ in at most t bits. Then
some start on the ring has a chain of consecutive segments whose cumulative differences never
exceed their share of t: for t = 3 no bit in the first segment, at most one in the first two, two in
the first three. Candidates are met by such chains, not by one segment: a key holds the first
segment whole and one half of the second (one of its halves must be equal, as at most one bit
differs), for t = 3 that is 24 of 64 bits, under eight (start, half) tables. Within a key's rows the
longer chain conditions prune before the full Hamming check. t may be 0 to MOST_BITS; a large one
has short keys, which meet many rows.

Equal fingerprints are one vertex. Rows of a key never leave as pairs: they are linked to the
least vertex of their component within the key, found by growing a component against rows that no
component holds yet, so a key gives fewer links than it has rows. Links go to distributed
connected components.

Edge cases: null and empty texts, and texts of white space alone, have the fingerprint zero and
link like any other; fewer words than a shingle are one shingle; null doc_ids keep their row,
with the component of their fingerprint; repeated rows stay; a text of any length is read whole;
an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pandas as pd
import zstandard as zstd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest

from avcurate.llm.common import fresh, map_values, n_parts, release, renamed, spread, stage
from avcurate.llm.components import connected_components
from avcurate.llm.repeats import packed, rows_by_id

MOST_BITS = 15


# --- fingerprints --------------------------------------------------------------------------------


def shingles(text: str, k: int) -> list[bytes]:
    words = text.encode("utf-8").lower().split()  # of bytes: A-Z alone, and white space of ASCII alone
    if len(words) <= k:
        return [b" ".join(words)] if words else []
    return list(map(b" ".join, zip(*(words[i:] for i in range(k)))))


def fingerprint(text: str, k: int = 3, seed: int = 42, block: int = 1 << 16) -> int:
    grams = shingles(text, k)
    if not grams:
        return 0
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(grams), block):
        h = np.fromiter(map(xxh64_intdigest, grams[at : at + block], repeat(seed)), dtype="<u8")
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(grams), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, k: int = 3, seed: int = 42) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long)."""

    def make():
        release()
        return lambda texts: [np.array([fingerprint(t or "", k, seed) for t in texts], dtype=np.uint64).view(np.int64)]

    return map_values(spread(docs.select(F.col("doc_id").cast("long"), "text")), "text", make, "fp long")


# --- candidates ------------------------------------------------------------------------------------


def segments(limit: int) -> list[int]:
    """Where the segments of the ring begin, and its end."""
    if not 0 <= limit <= MOST_BITS:
        raise ValueError(f"links differ in 0 to {MOST_BITS} bits, not in {limit}")
    return [round(64 * i / (limit + 1)) for i in range(limit + 2)]


def chain_keys(limit: int) -> list:
    """For each start and half: their bits, and start and half above them, in one long; none where links are equal fingerprints."""
    cut, out = segments(limit), []
    sizes = np.diff(cut).tolist()
    for start in range(limit + 1 if limit else 0):
        ring = F.shiftrightunsigned("fp", cut[start])
        if start:
            ring = ring.bitwiseOR(F.shiftleft("fp", 64 - cut[start]))
        first, second = sizes[start], sizes[(start + 1) % (limit + 1)]
        for half, (lo, n) in enumerate(((0, second // 2), (second // 2, second - second // 2))):
            part = F.shiftrightunsigned(ring, first + lo).bitwiseAND(F.lit((1 << n) - 1))
            key = F.shiftleft(part, first).bitwiseOR(ring.bitwiseAND(F.lit((1 << first) - 1)))
            out.append(key + F.lit((2 * start + half) << 52))
    return out


def linked(fps: np.ndarray, one: np.uint64, start: int, limit: int) -> np.ndarray:
    """Which of fps differ from ``one`` in at most ``limit`` bits, by the chain that begins at ``start``."""
    cut = segments(limit)
    diff = fps ^ one
    if start:
        diff = (diff >> np.uint64(cut[start])) | (diff << np.uint64(64 - cut[start]))
    at = np.arange(len(fps))
    ends = np.cumsum(np.roll(np.diff(cut), -start))
    for j in range(1, limit + 1):  # the first j + 1 segments may differ by their share
        part = diff[at] & np.uint64((1 << int(ends[j])) - 1)
        at = at[np.bitwise_count(part) <= limit * (j + 1) // (limit + 1)]
    return at


def stars(fps: np.ndarray, start: int, limit: int) -> list[tuple[int, int]]:
    """Links (fingerprint, least of its component) for components within one key's distinct rows."""
    out, left = [], np.sort(fps)
    while len(left) > 1:
        root, edge, left = left[0], [left[0]], left[1:]
        members = []
        while edge and len(left):
            at = linked(left, edge.pop(), start, limit)
            if len(at):
                found = left[at]
                members += found.tolist()
                edge += list(found)
                left = np.delete(left, at)
        out += [(m, int(root)) for m in members]
    return out


def links(distinct: DataFrame, limit: int = 3) -> DataFrame:
    """distinct (fp) -> (u, v): enough links for the components of pairs within ``limit`` bits."""
    keys = chain_keys(limit) or [F.lit(None).cast("long")]
    keyed = distinct.select("fp", F.explode(F.array(*keys)).alias("key")).where("key is not null")
    dealt = keyed.repartition(n_parts(distinct), "key").sortWithinPartitions("key")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        kept_k, kept_f = np.empty(0, np.int64), np.empty(0, np.uint64)

        def solve(keys: np.ndarray, fps: np.ndarray) -> pd.DataFrame:
            cut = np.flatnonzero(np.diff(keys)) + 1
            lo, hi = np.r_[0, cut], np.r_[cut, len(keys)]
            many = hi - lo > 1
            out = []
            for a, b in zip(lo[many], hi[many]):
                out += stars(fps[a:b], int(keys[a] >> 53), limit)
            uv = np.array(out, dtype=np.uint64).reshape(-1, 2).view(np.int64)
            return pd.DataFrame({"u": uv[:, 0], "v": uv[:, 1]})

        for b in batches:
            keys, fps = np.r_[kept_k, b.key.to_numpy()], np.r_[kept_f, b.fp.to_numpy().view(np.uint64)]
            if not len(keys):
                continue
            open_ = np.searchsorted(keys, keys[-1])  # the last key may go on in the next batch
            kept_k, kept_f = keys[open_:], fps[open_:]
            if open_:
                yield solve(keys[:open_], fps[:open_])
        if len(kept_k):
            yield solve(kept_k, kept_f)

    return dealt.mapInPandas(fresh(run), "u long, v long")


def fingerprint_components(fps: DataFrame, limit: int = 3) -> DataFrame:
    """fps (doc_id, fp) -> doc_id, fp, component_id: the smallest doc_id reachable."""
    classes = stage(fps.groupBy("fp").agg(F.min("doc_id").alias("first_doc")), "simhash-classes")
    found = connected_components(stage(links(classes.select("fp"), limit), "simhash-links"))
    grouped = classes.join(found.withColumnRenamed("id", "fp"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    least = stage(grouped.where("component <> fp").groupBy("component").agg(F.min("first_doc").alias("other_doc")), "simhash-least")
    named = (
        grouped.join(least, "component", "left")
        .join(classes.select(F.col("fp").alias("component"), F.col("first_doc").alias("root_doc")), "component", "left")
        .select("fp", F.least("first_doc", "other_doc", "root_doc").alias("component_id"))
    )
    return fps.join(stage(named, "simhash-named"), "fp").select("doc_id", "fp", "component_id")


def near_duplicates(docs: DataFrame, k: int = 3, limit: int = 3, seed: int = 42) -> DataFrame:
    """doc_id, fingerprint (16 hexadecimal digits), component_id of every document."""
    fps = stage(fingerprints(docs, k, seed), "simhash-fps")
    return fingerprint_components(fps, limit).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


# --- similar texts -------------------------------------------------------------------------------------
#
# A fingerprint within three bits means nearly equal texts. Texts of a similarity of 0.8 differ in up
# to a quarter of the bits, which no key of exact segments meets. So similar texts are met by
# fingerprints of small samples: a sample is the few shingles with the least mixed hashes, and its
# fingerprint their sum. Similar texts share samples often (0.8^3, a dozen times over); what meets is
# then compared by sketches of the least hashes, which are whole sets for texts of up to SKETCH shingles.
# Of longer texts the sketches only tell which cannot be similar: what they leave, down to MARGIN (five
# standard deviations) below the bound, is compared by whole sets, brought together by the components of
# these candidates; of a component above GROUP rows by its samples again, so that none fills a task.

SAMPLES, SAMPLE, SKETCH, MARGIN, GROUP = 12, 3, 128, 0.18, 512


def sketches(docs: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """doc_id, fp, keys (fingerprints of samples), sketch (least hashes, sorted), full (they are all), digest and size of the whole set."""
    odd = np.random.default_rng(seed).integers(0, 1 << 64, SAMPLES, dtype=np.uint64) | np.uint64(1)

    def one(text: str) -> tuple[int, list[int], bytes, bool, int, int]:
        grams = shingles(text, k)
        if not grams:
            return 0, [], b"", True, 0, 0
        h = np.fromiter(map(xxh64_intdigest, grams, repeat(seed)), np.uint64, len(grams))
        ones = np.zeros(64, np.int64)
        for at in range(0, len(h), 1 << 16):
            ones += np.unpackbits(h[at : at + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
        fp = np.packbits(2 * ones > len(h), bitorder="little").view(np.int64)[0]
        h = np.unique(h)
        keys, few = [], min(SAMPLE, len(h))
        for i, m in enumerate(odd):
            x = h * m
            x ^= x >> np.uint64(32)
            keys.append(int((np.partition(x, few - 1)[:few].sum(dtype=np.uint64) * m + np.uint64(i)).view(np.int64)))
        return int(fp), keys, h[:SKETCH].tobytes(), len(h) <= SKETCH, int(h.sum(dtype=np.uint64).view(np.int64)), len(h)

    def make():
        release()
        return lambda texts: list(zip(*[one(t or "") for t in texts]))

    return map_values(spread(docs.select(F.col("doc_id").cast("long"), "text")), "text", make, "fp long, keys array<long>, sketch binary, full boolean, digest long, size long")


def resemblance(a: np.ndarray, b: np.ndarray, whole: bool) -> float:
    """Jaccard similarity of two sets by their sketches; exact where both sketches are whole sets."""
    union = np.union1d(a, b)
    if not whole:
        union = union[:SKETCH]
    both = np.intersect1d(a, b, assume_unique=True)
    return float((both <= union[-1]).sum()) / len(union) if len(union) else 1.0


def grow(ids: list[int], sets: list[np.ndarray], whole: list[bool], similarity: float) -> list[tuple[int, int]]:
    """Star links of the components of the rows that are similar by their sketches or whole sets."""
    if len(ids) < 2:
        return []
    size, all_ = np.array([len(x) for x in sets]), np.array(whole)
    items, place = np.unique(np.concatenate(sets), return_inverse=True)
    row, mine = np.repeat(np.arange(len(ids)), size), np.split(place, np.cumsum(size)[:-1])
    held, marked = len(ids), np.zeros(len(items), bool)
    out, root, edge, left = [], 0, [0], np.arange(1, len(ids))
    while len(left):
        if not edge:
            root, edge, left = int(left[0]), [int(left[0])], left[1:]
            continue
        if 2 * len(left) < held:  # rows that left need not be looked at again
            stays = np.zeros(len(ids), bool)
            stays[left] = True
            row, place, held = row[stays[row]], place[stays[row]], len(left)
        i = edge.pop()
        marked[mine[i]] = True
        common = np.bincount(row[marked[place]], minlength=len(ids))[left]
        marked[mine[i]] = False
        union = size[i] + size[left] - common
        exact = all_[i] & all_[left]
        # what sketches share bounds the similarity from above, and is it for whole sets
        may = common >= similarity * np.where(exact, union, np.minimum(union, SKETCH)) - 1e-9
        take = may & exact & (common / np.maximum(union, 1) >= similarity)
        open_ = np.flatnonzero(may & ~exact)
        take[open_] = [resemblance(sets[i], sets[j], False) >= similarity for j in left[open_]]
        near = left[take].tolist()
        left = left[~take]
        edge += near
        out += [(ids[j], ids[root]) for j in near]
    return out


def similar_links(sketched: DataFrame, similarity: float) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(u, v, exact), the rows of equal sets as one, and the samples that some share: links that hold (exact), and candidates."""
    rep = stage(sketched.where("size(keys) > 0 and doc_id is not null").groupBy("digest", "size", "sketch", "full", "keys").agg(F.min("doc_id").alias("id")), "similar-rep")
    keyed = rep.select("id", F.explode(F.array_distinct("keys")).alias("key"))
    met = stage(keyed.groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key"), "similar-met")
    members = stage(keyed.join(met, "key"), "similar-members")
    rows = members.join(rep.select("id", "sketch", "full", "size"), "id")
    dealt = rows.repartition(n_parts(rep), "key").sortWithinPartitions("key", "id")
    odd = int(np.ceil(similarity * (SKETCH + 1) - 1e-9))  # a smaller whole set is not similar to any that is not whole

    def solve(rows: list[tuple[int, np.ndarray, bool, int]]) -> list[tuple[int, int, bool]]:
        out = []
        for exact, some in ((True, [r[:3] for r in rows if r[2]]), (False, [r[:3] for r in rows if r[3] >= odd])):
            if len(some) > 1 and exact | any(not r[2] for r in some):
                out += [(u, v, exact) for u, v in grow(*map(list, zip(*some)), similarity if exact else similarity - MARGIN)]
        return out

    def frame(links: list[tuple[int, int, bool]]) -> pd.DataFrame:
        return pd.DataFrame(links, columns=["u", "v", "exact"]).astype({"u": "int64", "v": "int64", "exact": bool})

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        key, held = None, []
        for b in batches:
            out = []
            for k, i, s, f, n in zip(b.key, b.id, b.sketch, b.full, b["size"]):
                if k != key:
                    out += solve(held)
                    key, held = k, []
                held.append((i, np.frombuffer(bytes(s), np.uint64), bool(f), n))
            yield frame(out)
        yield frame(solve(held))

    return stage(dealt.mapInPandas(run, "u long, v long, exact boolean"), "similar-candidates"), rep, members


def verified_links(docs: DataFrame, candidates: DataFrame, rep: DataFrame, members: DataFrame, k: int, similarity: float, seed: int = 42) -> DataFrame:
    """(u, v): links of the rows that candidates (u, v) connect, by their whole sets; parts whose sketches are all whole are left out."""
    comp = stage(connected_components(candidates).join(rep.select("id", "full"), "id"), "similar-parts")
    parts = comp.groupBy("component").agg(F.count("*").alias("n"), F.min("full").alias("known")).where("not known").select("component", "n")
    open_ = stage(comp.select("id", "component").join(parts, "component"), "similar-open")
    small = open_.where(F.col("n") <= GROUP).select("id", F.xxhash64("component").alias("g"))
    large = open_.where(F.col("n") > GROUP).join(members, "id").select("id", F.xxhash64("component", "key").alias("g"))
    groups = small.unionByName(large).groupBy("id").agg(F.collect_list("g").alias("gs"))
    texts = packed(spread(docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("rid"), "text")))
    rows = texts.join(groups.withColumnRenamed("id", "rid").hint("shuffle_merge"), "rid")

    def sets(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        d = zstd.ZstdDecompressor()
        for b in batches:
            for at in range(0, len(b), 500):
                out = []
                for rid, z, gs in zip(*(b[c].iloc[at : at + 500] for c in ("rid", "z", "gs"))):
                    grams = shingles(d.decompress(z).decode("utf-8") if z else "", k)
                    h = np.unique(np.fromiter(map(xxh64_intdigest, grams, repeat(seed)), np.uint64, len(grams))).tobytes()
                    out += [(g, rid, h) for g in gs]
                yield pd.DataFrame(out, columns=["g", "id", "h"])

    dealt = rows.mapInPandas(sets, "g long, id long, h binary").repartition(n_parts(rep), "g").sortWithinPartitions("g", "id")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        group, ids, held = None, [], []
        for b in batches:
            out = []
            for g, i, h in zip(b.g, b.id, b.h):
                if g != group:
                    out += grow(ids, held, [True] * len(ids), similarity)
                    group, ids, held = g, [], []
                ids.append(i)
                held.append(np.frombuffer(bytes(h), np.uint64))
            yield pd.DataFrame(out, columns=["u", "v"], dtype="int64")
        yield pd.DataFrame(grow(ids, held, [True] * len(ids), similarity), columns=["u", "v"], dtype="int64")

    return dealt.mapInPandas(run, "u long, v long")


def similar_documents(docs: DataFrame, k: int = 5, similarity: float = 0.8, limit: int = 3, seed: int = 42) -> DataFrame:
    """doc_id, component_id: documents linked by fingerprints within ``limit`` bits or by a similarity of ``similarity``."""
    sketched = stage(sketches(docs, k, seed), "similar-sketches")
    by_bits = stage(fingerprint_components(sketched.select("doc_id", "fp"), limit), "similar-bits")
    found, rep, members = similar_links(sketched, similarity)
    verified = verified_links(docs, found.where("not exact").select("u", "v"), rep, members, k, similarity, seed)
    copies = sketched.where("size(keys) > 0").join(rep.select("digest", "size", "id").hint("shuffle_merge"), ["digest", "size"]).where("doc_id <> id").select(F.col("doc_id").alias("u"), F.col("id").alias("v"))
    edges = found.where("exact").select("u", "v").unionByName(verified).unionByName(copies).unionByName(by_bits.where("doc_id <> component_id").select(F.col("doc_id").alias("u"), F.col("component_id").alias("v")))
    comp = connected_components(stage(edges, "similar-links"))
    return docs.select("doc_id").join(comp.withColumnRenamed("id", "doc_id"), "doc_id", "left").withColumn("component_id", F.coalesce("component", "doc_id")).drop("component")


def keep_one(docs: DataFrame, k: int = 5, similarity: float = 0.8, limit: int = 3, seed: int = 42) -> DataFrame:
    """The documents without all but one row of each component of ``similar_documents``: the one with the smallest doc_id.

    Where ids repeat or are null, rows are told apart, and those with a null id come last.
    """
    rows, texts, _ = rows_by_id(renamed(docs))
    found = similar_documents(texts.withColumnRenamed("rid", "doc_id"), k, similarity, limit, seed)
    gone = found.where("doc_id <> component_id").select(F.col("doc_id").alias("rid")).distinct()
    return rows.join(stage(gone, "simhash-gone"), "rid", "left_anti").drop("rid").toDF(*docs.columns)
