"""Embedding near-duplicates: random-hyperplane sign hashing, exact cosines, connected components.

Equal vectors are one class with a count. Each class has a key of ``bits`` signs under each of
several tables of seeded random hyperplanes, and a sketch of SKETCH further signs; bits follow the
number of classes, so that keys hold ``bucket`` rows on average, and the number of tables follows
bits, so that a pair at the threshold misses every table, or has too unlike sketches, with a
probability of at most ``miss``.

1. Keys meet with ids and sketches alone. A row that has no row of a near sketch under a key goes.
2. What is left meets with its vectors. Within a key all cosines are computed in blocks by matrix
   products in double precision. A pair counts in the first table where its keys agree, so that
   links are counted once without pairs ever leaving a task: what leaves are counts and, for each
   key, links to the least member of each component.

A key of more than CROWD rows is dealt as blocks of rows, each pair of blocks to a task of its own,
so no key fills one task; which keys these are is estimated and changes no result.

Edge cases: vectors that are null, empty, zero, or hold null or non-finite components, and rows
without vec_id, link with nothing and are kept; vectors of unlike lengths do not link; an id that
unlike vectors share is one vertex; repeated rows are linked copies; an empty table gives no rows;
extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from avcurate.llm.common import fresh, n_parts, stage
from avcurate.llm.components import connected_components


SKETCH, CROWD = 128, 4096


def plan_tables(classes: int, threshold: float, bucket: int = 1024, miss: float = 1e-6) -> tuple[int, int]:
    """bits of a key, number of tables."""
    bits = min(30, max(4, math.ceil(math.log2(max(1, classes) / bucket))) if classes else 4)
    hit = (1 - math.acos(threshold) / math.pi) ** bits
    return bits, math.ceil(math.log(miss / 2) / math.log(1 - hit))


def sketch_limit(threshold: float, miss: float = 1e-6) -> int:
    """In how many of SKETCH signs a pair at the threshold may differ, but for a probability of half of ``miss``."""
    p, tail = math.acos(threshold) / math.pi, 1.0
    for k in range(SKETCH + 1):
        tail -= math.comb(SKETCH, k) * p**k * (1 - p) ** (SKETCH - k)
        if tail <= miss / 2:
            return k
    return SKETCH


def keys_of(vectors: np.ndarray, bits: int, tables: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Keys under each table, and sketches of SKETCH signs as words of 64."""
    planes = np.random.default_rng([seed, vectors.shape[1]]).standard_normal((vectors.shape[1], bits * tables + SKETCH))
    signs = vectors @ planes > 0
    keys = signs[:, SKETCH:].reshape(len(vectors), tables, bits) @ (1 << np.arange(bits))
    return keys.astype(np.int32), np.packbits(signs[:, :SKETCH], axis=1).view(np.uint64)


def with_company(sketches: np.ndarray, part: np.ndarray | None, limit: int, block: int = 256) -> np.ndarray:
    """Which rows have another within ``limit`` signs; of another part only, where parts are given."""
    out = np.zeros(len(sketches), bool)
    for lo in range(0, len(sketches) - 1, block):
        here = sketches[lo : lo + block]
        near = np.bitwise_count(here[:, None, :] ^ sketches[None, lo:, :]).sum(axis=2, dtype=np.int32) <= limit
        near[np.arange(len(here)), np.arange(len(here))] = False
        if part is not None:
            near &= part[lo : lo + block, None] != part[None, lo:]
        out[lo : lo + block] |= near.any(axis=1)
        out[lo:] |= near.any(axis=0)
    return out


def bucket_links(v: np.ndarray, weight: np.ndarray, ids: np.ndarray, keys: np.ndarray, t: int, threshold: float, part: np.ndarray | None = None, block: int = 256):
    """For one key of table t: the links that each row gains here, and (member, least of component); of unlike parts only, where parts are given."""
    unit = v / np.sqrt((v * v).sum(axis=1))[:, None]
    gained, root = np.zeros(len(v), np.int64), np.arange(len(v))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for lo in range(0, len(v) - 1, block):
        i, j = np.nonzero(unit[lo : lo + block] @ unit[lo:].T >= threshold)
        i, j = (i + lo)[i < j], (j + lo)[i < j]
        if part is not None:
            other = part[i] != part[j]
            i, j = i[other], j[other]
        if t and len(i):
            new = ~(keys[i, :t] == keys[j, :t]).any(axis=1)
            i, j = i[new], j[new]
        np.add.at(gained, i, weight[j])
        np.add.at(gained, j, weight[i])
        for a in np.unique(i):
            for b in np.unique(root[j[i == a]]).tolist():
                x, y = find(int(a)), find(b)
                root[max(x, y)] = min(x, y)
    top = np.array([find(i) for i in range(len(v))])
    some, moved = gained > 0, top != np.arange(len(v))
    return [(int(ids[i]), int(gained[i]), None) for i in np.flatnonzero(some)] + [(int(ids[i]), 0, int(ids[top[i]])) for i in np.flatnonzero(moved)]


KEY = ["dim", "t", "key"]
PLACE = [*KEY, "p", "q"]  # a key's parts p and q meet; its rows say which is theirs


def dealt(rows: DataFrame, crowd: int, every: int) -> DataFrame:
    """Rows of KEY and class ``cid``, by place; ``own`` is the part of a row's key that it belongs to. Crowds are estimated by one of ``every`` classes."""
    some = rows.where(F.pmod(F.xxhash64("cid"), F.lit(every)) == 0) if every > 1 else rows
    crowds = stage(some.groupBy(*KEY).agg((F.count("*") * every).alias("rows")).where(F.col("rows") > crowd), "emb-crowds")
    if crowds.isEmpty():
        placed = rows.withColumns({"own": F.lit(0), "p": F.lit(0), "q": F.lit(0)})
    else:
        parts = F.coalesce(F.ceil(F.col("rows") / crowd), F.lit(1)).cast("int")
        placed = rows.join(crowds, KEY, "left").withColumn("parts", parts).withColumn("own", F.pmod(F.xxhash64("cid", F.lit(1)), "parts").cast("int"))
        placed = placed.withColumn("x", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).withColumns({"p": F.least("own", "x"), "q": F.greatest("own", "x")}).drop("rows", "parts", "x")
    return placed.repartition(n_parts(rows), *PLACE).sortWithinPartitions(*PLACE)


def by_place(rows: DataFrame, solve: Callable[[tuple, pd.DataFrame], pd.DataFrame], schema: str) -> DataFrame:
    """``solve`` for the rows of each place that has more than one."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[pd.DataFrame] = []
        last = None
        for b in batches:
            for at, g in b.groupby(PLACE, sort=True):
                if held and at != last:
                    if sum(map(len, held)) > 1:
                        yield solve(last, pd.concat(held))
                    held.clear()
                held.append(g)
                last = at
        if sum(map(len, held)) > 1:
            yield solve(last, pd.concat(held))

    return rows.mapInPandas(fresh(run), schema)


def bucket_rows(classes: DataFrame, threshold: float, bits: int, tables: int, seed: int, limit: int, crowd: int = CROWD, every: int = 1) -> DataFrame:
    """(id, gained, other) rows of all keys; classes: cid, id, n, vec. Vectors are dealt in the precision that they came in."""
    sent = np.float32 if classes.schema["vec"].dataType.elementType.typeName() == "float" else np.float64

    def hash_(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for dim, g in b.groupby(b.vec.map(len)):
                v = np.array(g.vec.tolist(), dtype=np.float64)
                keys, sketches = keys_of(v, bits, tables, seed)
                yield pd.DataFrame({"cid": g.cid.to_numpy(), "dim": dim, "id": g.id.to_numpy(), "n": g.n.to_numpy(), "vec": [x.tobytes() for x in v.astype(sent)], "keys": list(keys), "sketch": [x.tobytes() for x in sketches]})

    hashed = stage(classes.mapInPandas(hash_, "cid long, dim int, id long, n long, vec binary, keys array<int>, sketch binary"), "emb-keys", "zstd")

    def company(at: tuple, g: pd.DataFrame) -> pd.DataFrame:
        sketches = np.frombuffer(b"".join(g.sketch), np.uint64).reshape(len(g), -1)
        return g.loc[with_company(sketches, g.own.to_numpy() if at[3] != at[4] else None, limit), [*KEY, "cid"]]

    keyed = hashed.select("cid", "dim", "sketch", F.posexplode("keys").alias("t", "key"))
    left = stage(by_place(dealt(keyed, crowd, every), company, "dim int, t int, key int, cid long").distinct(), "emb-company")

    def solve(at: tuple, g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("id", kind="stable")
        v = np.frombuffer(b"".join(g.vec), sent).reshape(len(g), -1).astype(np.float64)
        rows = bucket_links(v, g.n.to_numpy(), g.id.to_numpy(), np.array(g["keys"].tolist()), at[1], threshold, g.own.to_numpy() if at[3] != at[4] else None)
        return pd.DataFrame({"id": [r[0] for r in rows], "gained": [r[1] for r in rows], "other": pd.array([r[2] for r in rows], dtype="Int64")}).astype({"id": "int64", "gained": "int64"})

    met = left.join(hashed.select("cid", "id", "n", "vec", "keys"), "cid")
    return by_place(dealt(met, crowd, 1), solve, "id long, gained long, other long")


def near_duplicates(vectors: DataFrame, threshold: float = 0.95, id_col: str = "vec_id", vec_col: str = "embedding", seed: int = 95, crowd: int = CROWD, **plan) -> DataFrame:
    """vec_id, n_links, component_id, kept of every row."""
    rows = vectors.select(F.col(id_col).alias("vec_id"), F.col(vec_col).alias("vec"))
    finite = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))
    good = F.col("vec_id").isNotNull() & F.col("vec").isNotNull() & F.forall("vec", finite) & F.exists("vec", lambda x: x != 0)
    rows = rows.withColumn("vec", F.when(F.coalesce(good, F.lit(False)), F.col("vec")))
    classes = rows.where("vec is not null").groupBy("vec").agg(F.min("vec_id").alias("id"), F.count("*").alias("n"))
    classes = stage(classes.withColumn("cid", F.monotonically_increasing_id()), "emb-classes")
    count = classes.count()
    bits, tables = plan_tables(count, threshold, **plan)
    # an id given to unlike vectors stands for one vertex; counts are then those of all its vectors
    limit = sketch_limit(threshold, plan.get("miss", 1e-6))
    found = stage(bucket_rows(classes.repartition(n_parts(classes)), threshold, bits, tables, seed, limit, crowd, 16 if count > 1_000_000 else 1), "emb-links")
    counts = found.groupBy("id").agg(F.sum("gained").alias("gained"))
    parts = connected_components(found.where("other is not null").select(F.col("id").alias("u"), F.col("other").alias("v")))
    named = stage(
        classes.join(counts, "id", "left").join(parts, "id", "left")
        .select("vec", (F.coalesce("gained", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id")),
        "emb-named",
    )
    out = rows.join(named, "vec", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
