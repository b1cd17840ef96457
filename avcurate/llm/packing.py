"""First-fit decreasing packing with a tournament tree of bin capacities, in randomised groups.

Documents become token ids (texts by ``tokens``) and an end id. Each is cut into pieces
of ``length`` tokens; such a full piece is a sequence of its own. The rests are dealt by a seeded
hash into groups of ``group_rows`` on average, and each group packs its rests by itself: longest
first, each into the first bin that has room. The bins are leaves of a tournament tree whose inner
nodes hold the largest capacity below them, so that the first bin with room is found from the root
in logarithmic time.

Edge cases: a null or empty text is one piece with the end id; a text of any length is cut; ties
go by document (its id as text), start and checksum; repeated rows are packed as documents of their own; an empty
table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import math
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StringType, StructField, StructType

from avcurate.llm.common import parts_of, spread, stage
from avcurate.llm.tokens import ids_of

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, salt long"
#: Sequences of full pieces are numbered from here, by task and place; groups' sequences lie below.
FULL = 1 << 62


class FirstFit:
    """Tournament tree over bins of one capacity."""

    def __init__(self, bins: int, capacity: int):
        self.leaves = 1 << max(0, (bins - 1).bit_length())
        self.tree = [capacity] * (2 * self.leaves)

    def place(self, size: int) -> int:
        """The first bin with room for ``size``; takes the room."""
        tree, at = self.tree, 1
        if tree[1] < size:
            raise ValueError("no bin has room")
        while at < self.leaves:
            at *= 2
            if tree[at] < size:
                at += 1
        bin_, tree[at] = at - self.leaves, tree[at] - size
        while at > 1:
            at //= 2
            best = max(tree[2 * at], tree[2 * at + 1])
            if tree[at] == best:
                break
            tree[at] = best
        return bin_


def first_fit_decreasing(sizes: list[int], capacity: int) -> list[tuple[int, int]]:
    """(bin, offset) for each of ``sizes``; equal sizes keep their order."""
    fit, used, out = FirstFit(max(1, len(sizes)), capacity), {}, [(0, 0)] * len(sizes)
    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        b = fit.place(sizes[i])
        out[i] = (b, used.get(b, 0))
        used[b] = used.get(b, 0) + sizes[i]
    return out


def token_pieces(docs: DataFrame, tokenizer: str, length: int = 2048, end_id: int = 1, seed: int = 7, with_ids: bool = False) -> DataFrame:
    """The pieces of every document, rests with sequence_id -1; with_ids adds their ids as little-endian 32-bit integers."""
    end = struct.pack("<I", end_id)
    names = [x.split()[0] for x in PIECES.split(", ")][1:] + ["ids"] * with_ids
    schema = PIECES + ", ids binary" * with_ids
    types = to_arrow_schema(StructType.fromDDL(schema)).types[1:]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part, row, full = ids_of(tokenizer), TaskContext.get().partitionId(), 0, 0
        for b in batches:
            for some in parts_of(b, "text"):
                out, doc = [], []
                for i, text in enumerate(some.column("text").to_pylist()):
                    ids = np.array(encode(text or ""), dtype="<u4").tobytes() + end
                    n, row = len(ids) // 4, row + 1
                    for start in range(0, n, length):
                        piece = ids[4 * start : 4 * (start + length)]
                        k = len(piece) // 4
                        own, full = (FULL + (part << 40) + full, full + 1) if k == length else (-1, full)
                        out.append((start, k, zlib.crc32(piece), n, own, zlib.crc32(b"%d %d %d" % (seed, part, row))) + ((piece,) if with_ids else ()))
                        doc.append(i)
                arrays = [pa.array(v, t) for v, t in zip(zip(*out), types)]
                yield pa.RecordBatch.from_arrays([some.column("doc_id").take(pa.array(doc)), *arrays], names=["doc_id", *names])

    return spread(docs.select(F.col("doc_id").cast("long"), "text")).mapInArrow(cut, schema)


def pack_pieces(pieces: DataFrame, capacity: int, groups: int) -> DataFrame:
    """sequence_id and offset for every piece; extra columns of the pieces stay."""
    names = [f.name for f in pieces.schema if f.name not in ("sequence_id", "salt")]
    full = pieces.where("sequence_id >= 0").select(*names, "sequence_id", F.lit(0).cast("long").alias("offset"))

    def pack(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values(["doc_text", "start", "ids_crc32", "doc_tokens"], kind="stable", ignore_index=True)
        placed = first_fit_decreasing(g.length.tolist(), capacity)
        g["sequence_id"] = [(int(g.grp[0]) << 32) + b for b, _ in placed]
        g["offset"] = [o for _, o in placed]
        return g[["doc_text", *names[1:], "sequence_id", "offset"]]

    rests = pieces.where("sequence_id < 0").select(F.col("doc_id").cast("string").alias("doc_text"), *names[1:], F.pmod(F.xxhash64("salt"), F.lit(groups)).alias("grp"))
    fields = StructType([StructField("doc_text", StringType()), *full.schema.fields[1:]])
    packed = rests.groupBy("grp").applyInPandas(pack, fields)  # ids as text: pandas keeps no null next to a long
    return full.unionByName(packed.select(F.col("doc_text").cast("long").alias("doc_id"), *full.columns[1:]))


def pack_documents(docs: DataFrame, tokenizer: str, length: int = 2048, end_id: int = 1, group_rows: int = 1024, seed: int = 7) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset of every piece."""
    pieces = stage(token_pieces(docs, tokenizer, length, end_id, seed), "pack-pieces")
    groups = max(1, math.ceil(pieces.where("sequence_id < 0").count() / group_rows))
    return pack_pieces(pieces, length, groups)
