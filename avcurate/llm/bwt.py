"""Repeated windows of anchored runs, by merging the Burrows-Wheeler transforms of shards.

A run is a stretch of a text whose windows of ``length`` units (bytes, or words) all hold one
anchor; windows can be equal only where their anchors are, at equal places. So of all suffixes only
those that begin at anchors need an order, and a shard's transform is, for each of them, the units
before it, one for each pass. The merge begins with the rows of the shards one after the other.

1. Refinement: one pass for each unit from the anchor on. A pass moves rows, stably, by that unit
   within the interval in which they agree so far. A border that first shows in pass h is a common
   prefix of h units. Only intervals that a pass splits are moved.
2. Extension: pass d puts the suffixes d - 1 units before the anchors, in their order, by the unit
   before them (the transform's step), which gives the order of the suffixes d units before. Rows
   that become neighbours have the least of the common prefixes between them, so nothing is
   compared or sorted anew. Neighbours whose common prefix from the anchor on is ``length - d`` or
   more begin equal windows: the repeated intervals.

Rows leave when their interval holds them alone or their text ends; an end is unlike every unit and
every other end. Units are compared themselves, no hashes of them. Empty input gives empty marks.
"""

from __future__ import annotations

import numpy as np


def _units(flat: np.ndarray, at: np.ndarray, there: np.ndarray) -> np.ndarray:
    return np.where(there, flat[np.clip(at, 0, len(flat) - 1)].astype(np.int32), np.int32(-1))


def _split(order: np.ndarray, begins: np.ndarray, units: np.ndarray) -> tuple[np.ndarray, np.ndarray] | None:
    """Slots of the rows in intervals that ``units`` (of the rows in order; -1 is an end) split, and their stable order by unit; None where none splits."""
    unlike = ~begins
    unlike[1:] &= (units[1:] != units[:-1]) | (units[1:] < 0)
    if not unlike.any():
        return None
    interval = np.cumsum(begins) - 1
    touched = np.zeros(interval[-1] + 1, bool)
    touched[interval[unlike]] = True
    slots = np.flatnonzero(touched[interval])
    return slots, np.lexsort((units[slots], interval[slots]))


def refine(order: np.ndarray, begins: np.ndarray, flat: np.ndarray, anchor: np.ndarray, left: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Order of rows by their units from the anchor on, within intervals, and each one's common prefix with the row before it; -1 between intervals.

    A row has ``left`` units from ``flat[anchor]`` on. ``order`` lists the rows by interval, ``begins`` its first rows.
    """
    order = order.copy()
    common = np.where(begins, -1, length).astype(np.int32)
    at = np.arange(len(order))  # the slots of rows whose interval has others
    begins = begins.copy()
    for h in range(length):
        keep = ~(begins & np.r_[begins[1:], True]) if len(begins) else begins
        if not keep.all():
            at, begins = at[keep], begins[keep]
        if not len(at):
            break
        rows = order[at]
        units = _units(flat, anchor[rows] + h, left[rows] > h)
        if (moved := _split(rows, begins, units)) is None:
            continue
        slots, by = moved
        to = at[slots]
        order[to] = rows[slots][by]
        now = units[slots][by]
        interval = np.cumsum(begins)[slots]
        border = np.r_[True, (now[1:] != now[:-1]) | (now[1:] < 0) | (interval[1:] != interval[:-1])]
        new = border & ~begins[slots]
        common[to[new]] = h
        begins[slots] |= border
    return order, common


def extend(order: np.ndarray, common: np.ndarray, flat: np.ndarray, anchor: np.ndarray, left: np.ndarray, length: int) -> np.ndarray:
    """marks[row, d]: the window that begins d units before the row's anchor also begins elsewhere. A row has ``left`` units before its anchor."""
    reach = int(left.max())
    marks = np.zeros((len(left), reach + 1), bool)
    common = common.copy()
    for d in range(reach + 1):
        alone = common < 0
        keep = ~(alone & np.r_[alone[1:], True]) if len(alone) else alone
        if not keep.all():
            order, common = order[keep], common[keep]
        if not len(order):
            break
        twice = np.flatnonzero(common >= length - d)
        marks[order[twice], d] = marks[order[twice - 1], d] = True
        units = _units(flat, anchor[order] - 1 - d, left[order] > d)
        if (moved := _split(order, common < 0, units)) is None:
            continue
        slots, by = moved
        among, interval = common[slots], np.cumsum(common < 0)[slots]
        now = units[slots][by]
        border = np.r_[True, (now[1:] != now[:-1]) | (now[1:] < 0) | (interval[1:] != interval[:-1])]
        order, common = order.copy(), common.copy()
        order[slots] = order[slots][by]
        # between rows that meet now, the least of the common prefixes that lay between them
        ends = np.stack([np.r_[0, by[:-1]], by], axis=1) + 1
        met = ~border
        least = np.full(len(by), -1, np.int32)
        if met.any():
            least[met] = np.minimum.reduceat(np.r_[among, np.int32(-1)], ends[met].ravel())[::2]
        common[slots] = least
    return marks


def merge(keys: np.ndarray, shards: list[np.ndarray], at: np.ndarray, length: int) -> list[np.ndarray]:
    """For each row (its units, with its anchor at ``at``), which of its windows begin elsewhere among the rows of its key too."""
    n = len(keys)
    if not n:
        return []
    sizes = np.array([len(x) for x in shards])
    flat = np.concatenate(shards)
    anchor = np.cumsum(sizes) - sizes + at
    order = np.argsort(keys, kind="stable")  # of a key, the shards one after the other
    begins = np.r_[True, keys[order][1:] != keys[order][:-1]]
    order, common = refine(order, begins, flat, anchor, np.minimum(sizes - at, length), length)
    marks = extend(order, common, flat, anchor, at, length)
    return [m[a - np.arange(k)] for m, a, k in zip(marks, at.tolist(), (sizes - length + 1).tolist())]
