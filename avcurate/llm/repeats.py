"""Repeated substrings across a corpus: which bytes lie in a string of ``length`` bytes that starts elsewhere too.

With ``words``, also those in a passage of so many words that starts elsewhere too, whatever white
space (of ASCII) lies between its words. Below, a text is then a row of bytes and a row of words;
what is said of bytes holds for each of the two, and neither meets the other.

Every window of ``length`` bytes has an anchor: the gram of ``gram`` bytes in it with the least
hash, the first of equals. The choice depends on the window's bytes alone, so equal windows have
equal anchors, and neighbouring windows mostly share theirs: a document becomes runs of windows
with one anchor each. A run is named by its anchor's hash and by the hashes of its first and last
window, which cover all its bytes.

1. Runs meet by anchor. A run whose anchor occurs once in the corpus holds no repeated window. A
   run with an equal twin is repeated whole (twins agree in two hashes of 64 bits: among n runs
   n^2 / 2^129 are expected to do so by chance). The others are contested, and so is one run of each
   set of twins where other runs share the anchor. A batch decides what it can
   by itself and sends one row for each of its (anchor, run) pairs at most, so that an anchor or a
   run that a large part of all documents shares sends a row for each batch, not for each document.
2. Contested runs are shards whose Burrows-Wheeler transforms are merged (``bwt.py``): runs of one
   anchor meet with their bytes, the interleave is refined, and common prefixes show the windows
   that occur twice, exactly. An anchor with more than GROUP unlike runs is split: its windows are
   dealt in blocks of BLOCK neighbours by the bytes that all windows of a block share, and blocks
   that are still too many window by window, where equal rows alone can meet.
3. Repeated windows and runs become removed intervals of their documents.

Edge cases: null texts are empty; documents below ``length`` bytes keep all; windows never cross
documents; equal or null ids are told apart by row; a text of any length is read whole; an empty
table gives no rows; extra columns are kept by ``remove_repeats`` and ignored by ``repeats``.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import lru_cache
from itertools import repeat

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard as zstd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType
from xxhash import xxh64_intdigest

from avcurate.llm import bwt
from avcurate.llm.common import fresh, map_values, n_parts, release, renamed, spread, stage, union_all

POSITION = 24  # bits of a position in a batch's buffer
UNDECIDED, CONTESTED_SENT, FULL, CONTESTED = range(4)
WHOLE = 8  # added to the kind of a run that stands for equal runs of its batch: it is repeated whole, whatever else it is
RUNS = "pk long, h long, e long, kind byte, rid long, first int, n int, at int, words boolean"
SPANS = "rid long, first int, n int, words boolean"
ROWS = "key long, words boolean, rid long, first int, n int, at int, units binary, twin boolean"
WORD_GRAM = 8
GROUP, BLOCK = 512, 16  # rows of one key above which it is split; windows of a block
PASSAGE_WORDS = 51  # of the shortest repeated passage that the query's text and the pipeline lose: more than 50
MERGED = 4 << 20  # bytes of rows that are merged at once; keys are never cut


@lru_cache(1)
def constants() -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20260)
    return rng.integers(0, 1 << 64, 256, dtype=np.uint64), rng.integers(0, 1 << 64, 80, dtype=np.uint64) | np.uint64(1)


def gram_hashes(buf: np.ndarray, length: int, gram: int) -> dict[int, np.ndarray]:
    """Hashes of the grams of 2^k bytes (or words, whose hashes buf has) at every place: of ``gram`` of them, and of the parts of a window of ``length``."""
    table, odd = constants()
    top = top_gram(length)
    parts = {gram, top, *(1 << k for k in range(top.bit_length()) if length % top >> k & 1)}
    h, size, out = table[buf] if buf.dtype == np.uint8 else buf, 1, {}
    while True:
        if size in parts:
            out[size] = h
        if size >= top or len(h) <= size:
            return out
        h = h[:-size] * odd[size.bit_length()] + h[size:]
        h ^= h >> np.uint64(29)
        size *= 2


def window_hashes(grams: dict[int, np.ndarray], at: np.ndarray, length: int) -> np.ndarray:
    """Hashes of the windows of ``length`` bytes at places ``at``, from those of its binary parts."""
    _, odd = constants()
    out, offset, left = np.zeros(len(at), np.uint64), 0, length
    for size in sorted(grams, reverse=True):
        while left >= size:
            out = (out ^ out >> np.uint64(31)) * odd[20 + size.bit_length()] + grams[size][at + offset]
            offset, left = offset + size, left - size
    return out ^ out >> np.uint64(32)


def top_gram(length: int) -> int:
    return 1 << min(8, length.bit_length() - 1)


def units_of(raw: bytes, words: bool) -> np.ndarray:
    """The bytes of a text, or the hashes of its words."""
    if words:
        return np.fromiter(map(xxh64_intdigest, raw.split(), repeat(20260)), np.uint64)
    return np.frombuffer(raw, np.uint8)


def runs_of(docs: list[np.ndarray], length: int, gram: int):
    """(doc, first, n, anchor, e, at) arrays for the runs of windows of some documents; at is the anchor's place from first on."""
    lens = np.array([len(d) for d in docs], dtype=np.int64)
    empty = np.empty(0, np.int64)
    buf = np.concatenate(docs)
    if len(buf) < length:
        return empty, empty, empty, empty.astype(np.uint64), empty.astype(np.uint64), empty
    grams = gram_hashes(buf, length, gram)
    h = grams[gram]
    low = np.uint64((1 << POSITION) - 1)
    least = h & ~low | np.arange(len(h), dtype=np.uint64)
    span, step = length - gram + 1, 1
    while 2 * step <= span:
        least = np.minimum(least[:-step], least[step:])
        step *= 2
    if span > step:
        least = np.minimum(least[: len(least) - (span - step)], least[span - step :])
    ends = np.cumsum(lens)
    starts = ends - lens
    first_last = [(s, e - length) for s, e in zip(starts.tolist(), ends.tolist()) if e - s >= length]
    if not first_last:
        return empty, empty, empty, empty.astype(np.uint64), empty.astype(np.uint64), empty
    change = np.empty(len(least), bool)
    change[0], change[1:] = True, least[1:] != least[:-1]
    ok = np.zeros(len(least) + 1, np.int8)
    for a, b in first_last:
        ok[a] += 1
        ok[b + 1] -= 1
        change[a] = True
    ok = np.cumsum(ok[:-1], dtype=np.int8).astype(bool)
    lo = np.flatnonzero(change & ok)
    doc = np.searchsorted(ends, lo, side="right")
    hi = np.minimum(np.r_[lo[1:], len(least)] - 1, ends[doc] - length)
    place = (least[lo] & low).astype(np.int64)
    anchor = h[place]
    _, odd = constants()
    e = (window_hashes(grams, lo, length) * odd[70] ^ window_hashes(grams, hi, length) * odd[71]) + (hi - lo).astype(np.uint64) * odd[72]
    return doc, lo - starts[doc], hi - lo + 1, anchor, e ^ e >> np.uint64(30), place - lo


def batches_of(rids: np.ndarray, texts, most: int = 3 << 19):
    """(rids, texts as bytes) in parts of about ``most`` bytes; a longer text is a part of its own."""
    part, ids, size = [], [], 0
    for rid, text in zip(rids, texts):
        raw = text if isinstance(text, bytes) else (text or "").encode("utf-8")
        if part and size + len(raw) > most:
            yield np.array(ids, np.int64), part
            part, ids, size = [], [], 0
        part.append(raw)
        ids.append(rid)
        size += len(raw)
    if part:
        yield np.array(ids, np.int64), part


def pieces_of(doc: np.ndarray, length: int, most: int = 8 << 20) -> list[tuple[int, np.ndarray]]:
    """A very long document in parts that overlap by a window less one byte."""
    if len(doc) <= most:
        return [(0, doc)]
    return [(at, doc[at : at + most]) for at in range(0, len(doc) - length + 1, most - length + 1)]


def decide_locally(anchor: np.ndarray, e: np.ndarray) -> np.ndarray:
    """kind of each run of a batch; those that only this batch's rows decide are FULL or CONTESTED.

    The first of each (anchor, e) keeps UNDECIDED and stands for the rest, which are FULL; of an
    anchor with several e, one row says so (CONTESTED_SENT) and the rest are CONTESTED. WHOLE is
    added to a first with a twin here: its twins' windows are not hashed, so it must not depend on them.
    """
    order = np.lexsort((e, anchor))
    a, x = anchor[order], e[order]
    new_a = np.r_[True, a[1:] != a[:-1]] if len(a) else np.empty(0, bool)
    new_e = new_a | np.r_[True, x[1:] != x[:-1]] if len(a) else new_a
    of_a, of_e = np.cumsum(new_a) - 1, np.cumsum(new_e) - 1
    twins = np.bincount(of_e)[of_e] > 1
    several = np.bincount(of_a[new_e])[of_a] > 1
    kind = np.full(len(a), UNDECIDED, np.int8)
    kind[twins & ~new_e] = FULL
    kind[several & new_e] = CONTESTED
    kind[several & new_a] = CONTESTED_SENT
    kind[twins & new_e] += WHOLE
    out = np.empty_like(kind)
    out[order] = kind
    return out


def find_runs(docs: DataFrame, length: int, gram: int, words: int | None = None) -> DataFrame:
    """docs (rid, text) -> rows of RUNS; decided rows have a place of their own, others meet by anchor."""

    def some_runs(rids: np.ndarray, texts: list[bytes], length: int, gram: int, of_words: bool) -> Iterator[pd.DataFrame]:
        parts = [(r, at, p) for r, t in zip(rids.tolist(), texts) for at, p in pieces_of(units_of(t, of_words), length)]
        step = len(parts) if len(parts) == len(texts) else 1  # the parts of a very long text go one by one
        for lo in range(0, len(parts), step):
            some = parts[lo : lo + step]
            doc, first, n, anchor, e, at = runs_of([p for *_, p in some], length, gram)
            if not len(doc):
                continue
            rid, base = np.array([r for r, *_ in some]), np.array([x for _, x, _ in some])
            kind = decide_locally(anchor, e)
            h = anchor.view(np.int64)
            pk = np.where(kind % WHOLE >= FULL, e.view(np.int64) ^ rid[doc], h)
            h = np.where(kind % WHOLE == CONTESTED, h, 0)  # of the others pk has it, or nothing asks for it
            yield pd.DataFrame({"pk": pk, "h": h, "e": e.view(np.int64), "kind": kind, "rid": rid[doc], "first": (base[doc] + first).astype(np.int32), "n": n.astype(np.int32), "at": at.astype(np.int32), "words": of_words})

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for rids, texts in batches_of(b.rid.to_numpy(), b.text):
                yield from some_runs(rids, texts, length, gram, False)
                if words:
                    yield from some_runs(rids, texts, words, min(WORD_GRAM, top_gram(words)), True)

    return docs.mapInPandas(fresh(run), RUNS)


def settle_runs(runs: DataFrame) -> DataFrame:
    """(rid, first, n, words, h, at, contested): runs repeated whole, and those whose windows must be compared; a run may be both."""
    dealt = runs.repartition(n_parts(runs), "pk").sortWithinPartitions("pk")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        left = None

        def solve(g: pd.DataFrame) -> pd.DataFrame:
            whole, kind = g.kind.to_numpy() >= WHOLE, g.kind.to_numpy() % WHOLE
            contested = (kind == CONTESTED) | (kind == CONTESTED_SENT)
            full = whole | (kind == FULL)
            own_h = np.where(kind < FULL, g.pk.to_numpy(), g.h.to_numpy())
            open_ = np.flatnonzero(kind < FULL)
            h, e, k = own_h[open_], g.e.to_numpy()[open_], kind[open_]
            order = np.lexsort((e, h))
            open_, h, e, k = open_[order], h[order], e[order], k[order]
            if len(h):
                new = np.r_[True, h[1:] != h[:-1]]
                of = np.cumsum(new) - 1
                varied = np.bincount(of, np.r_[False, (e[1:] != e[:-1]) & (h[1:] == h[:-1])] | (k == CONTESTED_SENT))[of] > 0
                twins = np.bincount(of)[of] > 1
                contested[open_[varied]] = True
                full[open_[~varied & twins]] = True
            take = np.r_[np.flatnonzero(full), np.flatnonzero(contested)]  # a run may be both
            return g[["rid", "first", "n", "words"]].assign(h=own_h, at=g["at"]).iloc[take].assign(contested=np.arange(len(take)) >= full.sum())

        for b in batches:
            if not len(b):
                continue
            g = b if left is None else pd.concat([left, b], ignore_index=True)
            pk = g.pk.to_numpy()
            at = int(np.searchsorted(pk, pk[-1]))
            left = g.iloc[at:]
            if at:
                yield solve(g.iloc[:at])
        if left is not None and len(left):
            yield solve(left)

    return dealt.mapInPandas(fresh(run), SPANS + ", h long, at int, contested boolean")


def packed(texts: DataFrame) -> DataFrame:
    """The rows with their ``text`` compressed, as ``z``, before they are dealt; null stays null."""

    def make():
        release()
        c = zstd.ZstdCompressor(level=1)
        return lambda texts: [[None if t is None else c.compress(t.encode("utf-8")) for t in texts]]

    return map_values(texts, "text", make, "z binary")


def with_lists(z: DataFrame, spans: DataFrame, how: str, columns: tuple[str, ...] = ("first", "n", "words")) -> DataFrame:
    """Packed texts with the lists of the ``columns`` of their spans. All calls of one plan take one frame of packed texts and read all of its columns, so that it deals them once."""
    lists = spans.groupBy("rid").agg(F.sort_array(F.collect_list(F.struct(*columns))).alias("s"))
    lists = lists.select("rid", *[F.col(f"s.{c}").alias(c) for c in columns])
    return z.join(lists.hint("shuffle_merge"), "rid", how)


def blocks_of(first: int, n: int, at: int, block: int) -> Iterator[tuple[int, int, int, int | None]]:
    """(first, n, at, block number) of the parts of a run whose windows have their anchor in one block of places; the run whole without ``block``."""
    if not block:
        yield first, n, at, None
        return
    j = 0
    while j < n:
        q = (at - j) // block
        k = min(n, at - q * block + 1) - j
        yield first + j, k, at - j, q
        j += k


def deal_runs(z: DataFrame, runs: DataFrame, lengths: tuple[int, int | None]) -> DataFrame:
    """ROWS: contested runs (rid, first, n, words, h, at, block) with their units, whole by their anchors, or in blocks by what the windows of a block share.

    Of equal rows of a batch the first has its units and is a ``twin``; the others, without units, are decided.
    """

    def rows(raw: bytes, rid: int, lists) -> Iterator[tuple]:
        split = None
        for first, n, of_words, h, at, block in zip(*lists):
            length = lengths[1] if of_words else lengths[0]
            if of_words and split is None:
                split = raw.split()
            for f, k, a, q in blocks_of(int(first), int(n), int(at), int(block)):
                units = split[f : f + k + length - 1] if of_words else raw[f : f + k + length - 1]
                key = int(h)
                if q is not None:  # the windows of block q hold so many units before the anchor, and up to there after it
                    core = units[max(0, a - q * block) : a + length - (q + 1) * block + 1]
                    key = xxh64_intdigest(b" ".join(core) if of_words else core, q) - (1 << 63)
                yield key, bool(of_words), rid, f, k, a, b" ".join(units) if of_words else units

    sent = to_arrow_schema(StructType.fromDDL(ROWS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        d = zstd.ZstdDecompressor()

        def send(held: list[tuple], seen: dict[tuple, int]) -> pa.RecordBatch:
            whole = [(*r, r[6] is not None and seen[r[1], r[0], r[5], r[4], r[6]] > 1) for r in held]
            return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(zip(*whole), sent.types)], schema=sent)

        for b in batches:
            b = b.select(["rid", "z", "first", "n", "words", "h", "at", "block"]).to_pandas()
            held, seen, size = [], {}, 0
            for z, rid, *lists in zip(b.z, b.rid, b["first"], b.n, b.words, b.h, b["at"], b.block):
                for r in rows(d.decompress(z), rid, lists):
                    same = r[1], r[0], r[5], r[4], r[6]
                    seen[same] = seen.get(same, 0) + 1
                    if seen[same] > 1:
                        held.append((r[0] ^ rid, *r[1:6], None))
                    else:
                        held.append(r)
                        size += len(r[6])
                if size > 8 << 20:
                    yield send(held, seen)
                    held, seen, size = [], {}, 0
            if held:
                yield send(held, seen)

    return with_lists(z, runs, "inner", ("first", "n", "words", "h", "at", "block")).mapInArrow(fresh(run), ROWS)


def merged_runs(rows: DataFrame, lengths: tuple[int, int | None]) -> DataFrame:
    """SPANS of the windows of ROWS that begin elsewhere too: transforms of the rows of a key are merged."""
    dealt = rows.repartition(n_parts(rows), "words", "key").sortWithinPartitions("words", "key")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def solve(g: pd.DataFrame) -> Iterator[pd.DataFrame]:
            open_ = g.units.notna()
            yield g.loc[~open_ | g.twin, ["rid", "first", "n", "words"]]
            for of_words, part in g[open_].groupby("words"):
                if of_words:
                    ids: dict[bytes, int] = {}
                    units = [np.array([ids.setdefault(w, len(ids)) for w in bytes(u).split()], np.int32) for u in part.units]
                else:
                    units = [np.frombuffer(u, np.uint8) for u in part.units]
                marks = bwt.merge(part.key.to_numpy(), units, part["at"].to_numpy(np.int64), lengths[of_words])
                flat = np.concatenate([np.r_[m, False] for m in marks]).astype(np.int8)
                edge = np.diff(np.r_[np.int8(0), flat])
                lo, hi = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
                size = np.array([len(m) + 1 for m in marks])
                starts = np.cumsum(size) - size
                row = np.searchsorted(starts, lo, side="right") - 1
                yield pd.DataFrame({"rid": part.rid.to_numpy()[row], "first": (part["first"].to_numpy()[row] + lo - starts[row]).astype(np.int32), "n": (hi - lo).astype(np.int32), "words": of_words})

        ready, size, tail = [], 0, None
        for b in batches:
            if not len(b):
                continue
            g = b if tail is None else pd.concat([tail, b], ignore_index=True)
            whole = int(((g.key != g.key.iloc[-1]) | (g.words != g.words.iloc[-1])).sum())
            ready, tail = [*ready, g.iloc[:whole]], g.iloc[whole:]
            size += sum(len(u) for u in ready[-1].units if u is not None)
            if size > MERGED:
                yield from solve(pd.concat(ready, ignore_index=True))
                ready, size = [], 0
        if tail is not None:
            yield from solve(pd.concat([*ready, tail], ignore_index=True))

    return dealt.mapInPandas(fresh(run), SPANS)


def contested_windows(z: DataFrame, contested: DataFrame, lengths: tuple[int, int | None]) -> list[DataFrame]:
    """SPANS of the windows of contested runs that begin elsewhere too; keys that many rows share are split."""
    spans = [x.split()[0] for x in SPANS.split(", ")]

    def crowded(rows: DataFrame, key: str) -> DataFrame:
        return stage(rows.groupBy("words", key).agg(F.count("*").alias("rows")).where(F.col("rows") > GROUP).select("words", key), "repeat-crowded")

    def runs(rows: DataFrame, block: int) -> DataFrame:
        return rows.select(*spans, "h", "at", F.lit(block).alias("block"))

    many = crowded(contested, "h")
    if many.isEmpty():
        return [merged_runs(deal_runs(z, runs(contested, 0), lengths), lengths)]
    blocks = stage(deal_runs(z.select("rid", "z"), runs(contested.join(many, ["words", "h"], "left_semi"), BLOCK), lengths), "repeat-blocks", "zstd")
    more = crowded(blocks.where("units is not null"), "key")
    rest = blocks.join(more, ["words", "key"], "left_semi")
    windows = rest.where("units is not null").withColumnRenamed("key", "h")
    alone = runs(contested.join(many, ["words", "h"], "left_anti"), 0).unionByName(runs(windows, 1))  # one pass over the texts for both
    return [
        merged_runs(deal_runs(z, alone, lengths), lengths),
        merged_runs(blocks.join(more, ["words", "key"], "left_anti"), lengths),
        rest.where("units is null or twin").select(*spans),
    ]


def rows_by_id(docs: DataFrame) -> tuple[DataFrame, DataFrame, bool]:
    """The documents with a row id ``rid``, (rid, text), and whether rid is doc_id; where ids repeat or are null it numbers a staged copy in the order of ids, nulls last."""
    odd = docs.groupBy("doc_id").count().where("count > 1 or doc_id is null").limit(1).count()
    if odd:
        docs = stage(docs.orderBy(F.asc_nulls_last("doc_id")).withColumn("rid", F.monotonically_increasing_id()), "repeat-docs")
    else:
        docs = docs.withColumn("rid", F.col("doc_id").cast("long"))
    return docs, spread(docs.select("rid", "text")), not odd


def repeated_spans(texts: DataFrame, z: DataFrame, length: int = 400, gram: int = 128, words: int | None = None) -> DataFrame:
    """(rid, first, n, words): starts of repeated windows, as intervals that may touch or overlap; z has the texts packed."""
    gram = min(gram, top_gram(length))
    settled = stage(settle_runs(find_runs(texts, length, gram, words)), "repeat-runs", "zstd")
    whole = settled.where("not contested").select("rid", "first", "n", "words")
    return union_all([whole, *contested_windows(z, settled.where("contested"), (length, words))])


def intervals(raw: bytes, first, n, words, length: int, n_words: int | None) -> tuple[np.ndarray, np.ndarray]:
    """Maximal covered byte intervals [lo, hi) of windows that start in [first, first + n)."""
    words = np.asarray(words, bool)
    lo = np.asarray(first, np.int64).copy()
    hi = lo + np.asarray(n, np.int64) + np.where(words, (n_words or 0) - 2, length - 1)
    if words.any():  # so far the first and the last word
        at = np.array([m.span() for m in re.finditer(rb"\S+", raw)])
        lo[words], hi[words] = at[lo[words], 0], at[hi[words], 1]
    order = np.argsort(lo, kind="stable")
    lo, hi = lo[order], np.maximum.accumulate(hi[order])
    new = np.r_[True, lo[1:] > hi[:-1]]
    return lo[new], hi[np.r_[np.flatnonzero(new)[1:] - 1, len(hi) - 1]]


def cleaned(z: DataFrame, spans: DataFrame, length: int, n_words: int | None = None, with_text: bool = False) -> DataFrame:
    """rid, n_bytes, n_removed, n_spans, kept_sha256 of every text, by repeated strings alone, and the other columns of z.

    with_text adds what is left without repeated passages too, and whether something was cut.
    """
    dealt = with_lists(z, spans, "left")
    others = [c for c in z.columns if c not in ("rid", "z")]
    own = StructType.fromDDL("rid long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", left string, cut boolean" * with_text)
    types = to_arrow_schema(own).types

    def without(raw: bytes, first, n, words) -> tuple[bytes, int, int]:
        if first is None or not len(first):
            return raw, 0, 0
        lo, hi = intervals(raw, first, n, words, length, n_words)
        return b"".join([raw[a:z] for a, z in zip([0, *hi.tolist()], [*lo.tolist(), len(raw)])]), int((hi - lo).sum()), len(lo)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        d = zstd.ZstdDecompressor()
        for batch in batches:
            b = batch.select(["rid", "z", "first", "n", "words"]).to_pandas()
            out, size, begin = [], 0, 0

            def send(out: list[tuple], begin: int) -> pa.RecordBatch:
                passed = [batch.column(c).slice(begin, len(out)) for c in others]
                return pa.RecordBatch.from_arrays([*(pa.array(v, t) for v, t in zip(zip(*out), types)), *passed], names=own.names + others)

            for rid, z, first, n, words in zip(b.rid, b.z, b["first"], b.n, b.words):
                raw, of_bytes = b"" if z is None else d.decompress(z), None if first is None else ~np.asarray(words, bool)
                kept, removed, parts = without(raw, *((None,) * 3 if first is None else (x[of_bytes] for x in (first, n, words))))
                row = (rid, len(raw), removed, parts, hashlib.sha256(kept).hexdigest())
                if with_text:
                    left = kept if first is None or of_bytes.all() else without(raw, first, n, words)[0]
                    row += (None if z is None else left.decode("utf-8", "ignore"), len(left) < len(raw))
                    size += len(left)
                out.append(row)
                if len(out) >= 2000 or size > 4 << 20:
                    yield send(out, begin)
                    out, size, begin = [], 0, begin + len(out)
            if out:
                yield send(out, begin)

    return dealt.mapInArrow(fresh(run), StructType(own.fields + [z.schema[c] for c in others]))


def repeats(docs: DataFrame, length: int = 400, words: int | None = None, **options) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every document, by repeated strings of ``length`` bytes.

    With ``words``, also text: what is left when repeated passages of so many words go too (null texts stay null).
    """
    rows, texts, same = rows_by_id(docs.select("doc_id", "text"))
    z = packed(texts)
    out = cleaned(z, repeated_spans(texts, z, length, words=words, **options), length, words, words is not None)
    columns = ["n_bytes", "n_removed", "n_spans", "kept_sha256", *[F.col("left").alias("text")] * bool(words)]
    if same:
        return out.select(F.col("rid").alias("doc_id"), *columns)
    return rows.select("rid", "doc_id").join(out, "rid").select("doc_id", *columns)


def remove_repeats(docs: DataFrame, length: int = 400, words: int | None = None, **options) -> DataFrame:
    """The documents with the bytes of repeated strings, and of repeated passages of ``words`` words, removed from their texts.

    A character of which a part is removed goes whole; null texts stay null; n_chars, where it
    exists, follows the new text.
    """
    own = renamed(docs, ("doc_id", "text", "n_chars"))
    rows, texts, _ = rows_by_id(own)
    z = packed(spread(rows))  # with all columns, so that no text meets its row again
    out = cleaned(z, repeated_spans(texts, z, length, words=words, **options), length, words, True)
    new = {"text": F.col("left"), "n_chars": F.when(F.col("cut"), F.length("left").cast("long")).otherwise(F.col("n_chars"))}
    return out.select(*[new.get(c, F.col(c)) for c in own.columns]).toDF(*docs.columns)
