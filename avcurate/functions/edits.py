"""Edit distances and alignments of many utterances at once, by bit vectors over NumPy arrays.

A column of an edit table is kept as the signs of its vertical differences, 64 places a word, and
one step of all pairs of a chunk is a few operations on words. Any length of utterance is measured.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from avcurate.functions.text import BREAK

#: Characters of texts that are measured at once, pairs of a step, and bytes of kept columns.
SLICE_CHARS, STEP_PAIRS, KEPT_BYTES = 2_000_000, 4096, 32_000_000
TABLE_WORDS = 4 << 20  # words of a table of the places of codes
HIT, SUB, DEL, INS = range(4)
ONE, TOP = np.uint64(1), np.uint64(63)


class Pairs:
    """Utterances of texts that answer each other, as places in one array of codes; 0 is no character."""

    def __init__(self, hyps: list[str], refs: list[str]):
        points = np.frombuffer((BREAK.join([*hyps, *refs]) + BREAK).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        ends = np.flatnonzero(points == ord(BREAK))
        starts = np.r_[0, ends[:-1] + 1]
        seen = np.zeros(int(points.max()) + 1, dtype=bool)
        seen[points] = True
        seen[ord(BREAK)] = False
        dense = np.cumsum(seen) * seen
        self.codes = dense.astype(np.uint8 if dense.max() < 256 else np.uint16 if dense.max() < 65536 else np.uint32)[points]
        n = np.array([t.count(BREAK) + 1 for t in [*hyps, *refs]], dtype=np.int64)
        first = np.cumsum(n) - n
        rows = len(hyps)
        most = np.maximum(n[:rows], n[rows:])
        self.row = np.repeat(np.arange(rows), most)
        at = np.arange(len(self.row)) - np.repeat(np.cumsum(most) - most, most)

        def side(n, first):
            has = at < n[self.row]
            which = np.where(has, first[self.row] + at, 0)
            return starts[which], np.where(has, ends[which] - starts[which], 0)

        self.h, self.h_len = side(n[:rows], first[:rows])
        self.r, self.r_len = side(n[rows:], first[rows:])


def slices(hyps: list[str], refs: list[str]) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about SLICE_CHARS characters; one longer text is a range of its own."""
    begin = size = 0
    for i, (h, r) in enumerate(zip(hyps, refs)):
        if size and size + len(h) + len(r) > SLICE_CHARS:
            yield begin, i
            begin, size = i, 0
        size += len(h) + len(r) + 1
    if begin < len(hyps):
        yield begin, len(hyps)


def within(codes, a, a_len, b, b_len) -> np.ndarray:
    """Whether a is what is left of b without some of its characters, for each pair."""
    out = np.empty(len(a), dtype=bool)
    order = np.argsort(-b_len, kind="stable")
    for k in range(0, len(order), STEP_PAIRS):
        o = order[k : k + STEP_PAIRS]
        at, x, n = a[o], b[o], -b_len[o]
        end = at + a_len[o]
        for j in range(-int(n[0])):
            if j % 16 == 0 and j:
                # those that are through, and those whose rest is too long, leave
                left = (at < end) & (end - at <= -n - j)
                out[o[~left]] = at[~left] == end[~left]
                o, at, end, x, n = o[left], at[left], end[left], x[left], n[left]
            live = int(np.searchsorted(n, -j))
            at[:live] += codes[at[:live]] == codes[x[:live] + j]
        out[o] = at == end
    return out


def mismatches(codes, a, b, length) -> np.ndarray:
    """Places where strings of one length differ."""
    out = np.zeros(len(a), dtype=np.int64)
    order = np.argsort(-length, kind="stable")
    for k in range(0, len(order), STEP_PAIRS):
        o = order[k : k + STEP_PAIRS]
        x, y, n, total = a[o], b[o], -length[o], np.zeros(len(o), dtype=np.int64)
        for j in range(-int(n[0])):
            live = int(np.searchsorted(n, -j))
            total[:live] += codes[x[:live] + j] != codes[y[:live] + j]
        out[o] = total
    return out


def matches(codes, p, p_len, words: int):
    """A function of codes, one for each of the first ``live`` patterns: the places that hold them, as words of bits.

    Few codes have a table of their places in each pattern; otherwise all places are compared each time.
    """
    n = len(p)
    size = int(codes.max()) + 1 if n else 1
    if size * words * n <= TABLE_WORDS:
        table, row = np.zeros((words, size * n), dtype=np.uint64), np.arange(n)
        for k in range(int(p_len.max()) if n else 0):
            has = row[p_len > k]
            table[k >> 6, codes[p[has] + k].astype(np.int64) * n + has] |= ONE << np.uint64(k & 63)
        return lambda c, live: table.take(c.astype(np.int64) * n + row[:live], axis=1)
    place = np.arange(64 * words)
    cells = np.where(place < p_len[:, None], codes[np.minimum(p[:, None] + place, len(codes) - 1)], 0)
    cells = np.ascontiguousarray(cells.astype(codes.dtype).reshape(n, words, 64).transpose(1, 0, 2))
    return lambda c, live: np.packbits((cells[:, :live] == c[:, None]).reshape(-1), bitorder="little").view(np.uint64).reshape(words, live)


def columns(codes, p, p_len, t, t_len, words: int, keep: bool = False):
    """Last columns (positive, negative differences) of the tables of patterns p and texts t, the longest text first.

    With ``keep`` also, for each step, the places where the diagonal stays equal and those of positive differences.
    """
    n = len(p)
    equal = matches(codes, p, p_len, words)
    vp, vn = np.full((words, n), ~np.uint64(0)), np.zeros((words, n), dtype=np.uint64)
    steps = int(t_len[0]) if n else 0
    kept = np.empty((2, steps, words, n), dtype=np.uint64) if keep else None
    falling = -t_len
    for j in range(steps):
        live = int(np.searchsorted(falling, -j))
        eq = equal(codes[t[:live] + j], live)
        p_, n_ = vp[:, :live], vn[:, :live]
        both = eq & p_
        total = both + p_
        if words > 1:
            carry = total[0] < both[0]
            for w in range(1, words):
                over = total[w] < both[w]
                total[w] += carry
                carry = over | (carry & (total[w] == 0))
        same = (total ^ p_) | eq | n_
        hp, hn = n_ | ~(same | p_), same & p_
        up, un = hp << ONE, hn << ONE
        up[0] |= ONE
        if words > 1:
            up[1:] |= hp[:-1] >> TOP
            un[1:] |= hn[:-1] >> TOP
        vp[:, :live], vn[:, :live] = un | ~(same | up), up & same
        if keep:
            kept[0, j, :, :live], kept[1, j, :, :live] = same, vp[:, :live]
    return vp, vn, kept


def chunks(p_len, t_len, keep: bool = False) -> Iterator[tuple[np.ndarray, int]]:
    """Pairs whose patterns have equally many words, the longest texts first, and that number."""
    words = np.maximum(1, (p_len + 63) // 64)
    order = np.lexsort((-t_len, words))
    k = 0
    while k < len(order):
        w = int(words[order[k]])
        most = max(1, STEP_PAIRS * 4 // w if w > 4 else STEP_PAIRS)
        if keep:
            most = max(1, min(most, KEPT_BYTES // (16 * w * max(1, int(t_len[order[k]])))))
        o = order[k : k + most]
        o = o[words[o] == w]
        yield o, w
        k += len(o)


def distances(hyps: list[str], refs: list[str]) -> np.ndarray:
    """Sum of the edit distances of the utterances of each pair of transcripts; equal pairs are measured once."""
    number: dict[tuple[str, str], int] = {}
    which = [number.setdefault(pair, len(number)) for pair in zip(hyps, refs)]
    hyps, refs = ([pair[side] for pair in number] for side in (0, 1))
    out = np.zeros(len(hyps), dtype=np.int64)
    for begin, end in slices(hyps, refs):
        x = Pairs(hyps[begin:end], refs[begin:end])
        out[begin:end] = np.bincount(x.row, _distances(x), end - begin).astype(np.int64)
    return out[which]


def _distances(x: Pairs) -> np.ndarray:
    """Where the shorter one lies within the longer one, the difference of lengths; up to two mismatches of equal lengths; else by columns."""
    swap = x.h_len > x.r_len
    a, b = np.where(swap, x.r, x.h), np.where(swap, x.h, x.r)
    m, n = np.where(swap, x.r_len, x.h_len), np.where(swap, x.h_len, x.r_len)
    d = n - m
    open_ = np.flatnonzero(m > 0)
    open_ = open_[~within(x.codes, a[open_], m[open_], b[open_], n[open_])]
    even = open_[d[open_] == 0]
    if len(even):
        few = mismatches(x.codes, a[even], b[even], m[even])
        d[even[few <= 2]] = few[few <= 2]
        open_ = np.setdiff1d(open_, even[few <= 2], assume_unique=True)
    for o, words in chunks(m[open_], n[open_]):
        o = open_[o]
        vp, vn, _ = columns(x.codes, a[o], m[o], b[o], n[o], words)
        bits = np.clip(m[o] - 64 * np.arange(words)[:, None], 0, 64)
        mask = np.where(bits == 64, ~np.uint64(0), (ONE << (bits % 64).astype(np.uint64)) - ONE)
        d[o] = n[o] + np.bitwise_count(vp & mask).sum(0, dtype=np.int64) - np.bitwise_count(vn & mask).sum(0, dtype=np.int64)
    return d


def alignments(x: Pairs) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Chunks of pairs (their numbers) and their operations as columns, from the end backwards; -1 after the last one.

    Among shortest alignments a match goes first, then sub, del, ins, as in ``udfs.align``.
    """
    for o, words in chunks(x.r_len, x.h_len, keep=True):
        h, r, i, j = x.h[o] - 1, x.r[o] - 1, x.h_len[o].copy(), x.r_len[o].copy()
        _, _, kept = columns(x.codes, x.r[o], x.r_len[o], x.h[o], x.h_len[o], words, keep=True)
        ops = np.full((int((i + j).max()), len(o)), -1, dtype=np.int8)
        live, step = np.flatnonzero(i + j), 0
        while len(live):
            p, q = i[live], j[live]
            word, bit = np.maximum(q - 1, 0) >> 6, (np.maximum(q - 1, 0) & 63).astype(np.uint64)
            op = np.where(p == 0, DEL, INS)
            inner = np.flatnonzero((p > 0) & (q > 0))
            if len(inner):
                who, row = live[inner], p[inner] - 1
                same = kept[0, row, word[inner], who] >> bit[inner] & ONE
                more = kept[1, row, word[inner], who] >> bit[inner] & ONE
                equal = x.codes[h[who] + p[inner]] == x.codes[r[who] + q[inner]]
                op[inner] = np.where(equal, HIT, np.where(same == 0, SUB, np.where(more == 1, DEL, INS)))
            ops[step, live] = op
            i[live] = p - (op != DEL)
            j[live] = q - (op != INS)
            live = live[i[live] + j[live] > 0]
            step += 1
        yield o, ops[:step]


def operation_counts(hyps: list[str], refs: list[str]) -> np.ndarray:
    """hit, sub, del and ins of each pair of transcripts, as rows."""
    out = np.zeros((len(hyps), 4), dtype=np.int64)
    for begin, end in slices(hyps, refs):
        x = Pairs(hyps[begin:end], refs[begin:end])
        for o, ops in alignments(x):
            for op in range(4):
                out[begin:end, op] += np.bincount(x.row[o], (ops == op).sum(0), end - begin).astype(np.int64)
    return out


def operation_rows(hyps: list[str], refs: list[str]) -> Iterator[tuple[np.ndarray, ...]]:
    """Operations of transcripts in order, as columns: number of the pair, place, operation, places in hyp and ref without breaks."""
    for begin, end in slices(hyps, refs):
        x = Pairs(hyps[begin:end], refs[begin:end])
        many = np.zeros(len(x.row), dtype=np.int64)
        parts = []
        for o, ops in alignments(x):
            many[o] = (ops >= 0).sum(0)
            parts.append((o, ops.T[:, ::-1][(ops.T >= 0)[:, ::-1]]))
        first = np.cumsum(many) - many
        op = np.empty(int(many.sum()), dtype=np.int8)
        for o, flat in parts:
            n = many[o]
            op[np.repeat(first[o] - (np.cumsum(n) - n), n) + np.arange(len(flat))] = flat
        row = np.repeat(x.row, many)
        new = np.r_[True, row[1:] != row[:-1]][: len(row)]

        def within_row(steps):
            before = np.cumsum(steps) - steps
            starts = before[new]
            return before - np.repeat(starts, np.diff(np.r_[np.flatnonzero(new), len(row)]))

        yield begin + row, within_row(np.ones(len(row), dtype=np.int64)), op, within_row((op != DEL).astype(np.int64)), within_row((op != INS).astype(np.int64))
