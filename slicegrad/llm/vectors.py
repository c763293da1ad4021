"""Embedding near-duplicates through an inverted multi-index.

Vectors are halved; each half has a codebook, and the product of the codebooks is a grid of cells. A vector lives in
its nearest cell and also visits the next nearest, in the order of a multi-sequence traversal (least sum of the two
halves' distances). Two vectors of one label meet where one is at home and the other is at home or visits; there the
cosine is computed in double precision. The grid fits the largest label, and how many cells are visited is set on a sample, so
that the share of the hardest close pairs that meet reaches a target.

Equal vectors are one class with a count first, so copies meet nobody. A crowded cell is dealt out as pairs of
chunks, so no task holds a cell; a meeting gives each class a sum of links and the edges of a spanning forest, never
its pairs. A pair that could meet in two cells counts in the one with the smaller number. Vectors go to their cells
in one exchange; elsewhere digests stand for them.

Rows whose vector is null, empty, zero or holds null or non-finite parts, or whose label is null, link with nothing
and are their own component. Vectors of different lengths are never compared. Repeated rows are copies of one class;
a null id is a component's id only if all its ids are null. An empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slicegrad.llm.common import cut, ship_by_value
from slicegrad.llm.components import components

ship_by_value(__name__)

SAMPLE = 20_000
QUERIES = 400
#: Rows of the largest label that a cell should be home to.
CELL_ROWS = 256
CODES = (4, 2048)
VISITS = (3, 48)
#: Share of pairs at exactly the least cosine that should meet; closer pairs meet more often.
TARGET_RECALL = 0.95
CHUNK = 4096
BLOCK = 256
#: Crowded cells up to this number are broadcast, some 3 MB; more are joined by an exchange.
BROADCAST_CELLS = 100_000


def codebook(points: np.ndarray, codes: int, rounds: int = 12, seed: int = 5) -> np.ndarray:
    """k-means centres; fewer than ``codes`` if there are fewer points."""
    rng = np.random.default_rng(seed)
    centres = points[rng.permutation(len(points))[: max(1, codes)]].copy()
    for _ in range(rounds):
        nearest = squares(points, centres).argmin(1)
        sums = np.zeros_like(centres)
        np.add.at(sums, nearest, points)
        n = np.bincount(nearest, minlength=len(centres))
        centres[n > 0] = sums[n > 0] / n[n > 0, None]
    return centres


def squares(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum((a * a).sum(1)[:, None] - 2 * a @ b.T + (b * b).sum(1), 0)


def traversal(unit: np.ndarray, books: tuple[np.ndarray, np.ndarray], visits: int) -> np.ndarray:
    """Cells by nearness, (rows, visits).

    The t nearest cells of a grid of two sorted sequences lie where (i + 1)(j + 1) <= t, so sums over that staircase
    in order give what stepping along the two sequences gives, for all rows at once. Missing cells are -1.
    """
    half = unit.shape[1] // 2
    d = [squares(unit[:, :half], books[0]), squares(unit[:, half:], books[1])]
    order = [np.argsort(x, axis=1, kind="stable")[:, :visits] for x in d]
    steps = [(i, j) for i in range(order[0].shape[1]) for j in range(min(order[1].shape[1], visits // (i + 1)))]
    i, j = np.array(steps).T
    near = [np.take_along_axis(x, o, axis=1) for x, o in zip(d, order)]
    sums = near[0][:, i] + near[1][:, j]
    best = np.argsort(sums, axis=1, kind="stable")[:, :visits]
    cells = np.take_along_axis(order[0][:, i] * len(books[1]) + order[1][:, j], best, axis=1)
    return np.pad(cells, ((0, 0), (0, visits - cells.shape[1])), constant_values=-1).astype(np.int32)


def unit_rows(rows) -> np.ndarray:
    x = np.array([np.asarray(r, dtype=np.float64) for r in rows])
    with np.errstate(over="ignore"):
        scale = np.abs(x).max(1, keepdims=True)
        x = x / scale  # so that squares neither overflow nor vanish
        return x / np.sqrt((x * x).sum(1, keepdims=True))


def fit_index(sample: np.ndarray, n: int, least: float, target: float = TARGET_RECALL, seed: int = 5) -> tuple[tuple[np.ndarray, np.ndarray], int]:
    """Codebooks for ``n`` vectors of one label, and how many cells a vector visits.

    The number is taken on made pairs, the hardest ones that count: sample vectors turned to a cosine of ``least``.
    Where the most visits don't bring the target, the grid is made coarser until they do.
    """
    codes = int(np.clip(np.sqrt(n / CELL_ROWS), *CODES))
    half = sample.shape[1] // 2
    rng = np.random.default_rng(seed)
    own = sample[rng.permutation(len(sample))[:QUERIES]]
    turned = rng.normal(size=own.shape)
    turned -= (turned * own).sum(1, keepdims=True) * own
    turned /= np.maximum(np.sqrt((turned * turned).sum(1, keepdims=True)), 1e-300)
    other = least * own + np.sqrt(1 - least * least) * turned
    while True:
        books = codebook(sample[:, :half], codes, seed=seed), codebook(sample[:, half:], codes, seed=seed + 1)
        a, b = traversal(own, books, VISITS[1]), traversal(other, books, VISITS[1])
        met_at = [np.where(x == y[:, :1], np.arange(VISITS[1]), VISITS[1]).min(1) for x, y in ((a, b), (b, a))]
        visits = int(np.quantile(np.minimum(*met_at), target, method="higher")) + 1
        if visits <= VISITS[1] or codes == 1:
            return books, max(VISITS[0], min(visits, VISITS[1]))
        codes //= 2


def usable(vector: Column, label: Column) -> Column:
    fine = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return F.coalesce(label.isNotNull() & vector.isNotNull() & (F.size(vector) > 0) & fine & F.exists(vector, lambda x: x != 0), F.lit(False))


def _placed(books: dict):
    """(cid, label, copies, vector) with the vector's length and the cells that the class visits, its home first."""

    def run(frames):
        for f in frames:
            for at in range(0, len(f), 1000):
                part = f.iloc[at : at + 1000]
                for dim, own in part.groupby(part["vector"].map(len)):
                    cells = traversal(unit_rows(own["vector"]), *books[dim])
                    yield own.assign(dim=np.int32(dim), cells=[c[c >= 0] for c in cells])

    return run


def meet(cell: int, f: pd.DataFrame, least: float) -> pd.DataFrame | None:
    """What one chunk pair of a cell gives: (a, null, links) sums and (a, b, null) forest edges.

    Rows at home, a block at a time, are compared with all; only these carry the list of cells that they visit.
    """
    unit = unit_rows(f["vector"])
    home, side, copies, cid = (f[c].to_numpy() for c in ("home", "side", "copies", "cid"))
    at_home, place = home == cell, np.arange(len(f))
    sided = (side != side[0]).any()
    near = np.zeros((len(f), len(f)), dtype=bool)
    hosts = np.flatnonzero(at_home)
    for lo in range(0, len(hosts), BLOCK):
        own = hosts[lo : lo + BLOCK]
        close = unit[own] @ unit.T >= least
        close &= ~at_home | (place > own[:, None])
        if sided:
            close &= side[own][:, None] != side
        i, j = np.nonzero(close)
        earlier = home[j] < cell  # such a guest's home may have met the host too
        if earlier.any():
            visits = f["visits"].iloc[own].tolist()
            wide = np.full((len(own), max(map(len, visits))), -1)
            for k, v in enumerate(visits):
                wide[k, : len(v)] = v
            earlier[earlier] = (wide[i[earlier]] == home[j[earlier]][:, None]).any(1)
        i, j = own[i[~earlier]], j[~earlier]
        near[i, j] = near[j, i] = True
    some = np.flatnonzero(near.any(1))
    if not len(some):
        return None
    links = [int(copies[near[k]].sum()) for k in some]
    rest = np.zeros(len(f), dtype=bool)
    rest[some] = True
    a, b = [], []
    for start in some:
        if rest[start]:
            rest[start] = False
            reached = [start]
            while reached:
                node = reached.pop()
                found = np.flatnonzero(near[node] & rest)
                rest[found] = False
                reached += list(found)
                a += [cid[node]] * len(found)
                b += list(cid[found])
    return pd.DataFrame({
        "a": np.r_[cid[some], np.array(a, dtype=np.int64)], "b": pd.array([None] * len(some) + b, dtype="Int64"),
        "n": pd.array(links + [None] * len(a), dtype="Int64"),
    })


def _met(least: float):
    keys = ["label", "dim", "cell", "lo", "hi"]

    def settled(f):
        for key, own in f.groupby(keys, sort=False):
            if len(own) > 1 and (out := meet(key[2], own, least)) is not None:
                yield out

    def run(frames):
        held = None  # rows come sorted by key; the last one may go on
        for f in frames:
            f = f if held is None else pd.concat([held, f], ignore_index=True)
            last = (f[keys] == f[keys].iloc[-1]).all(axis=1).to_numpy()
            cut_at = int(np.argmax(last))
            held = f.iloc[cut_at:]
            if cut_at:
                yield from settled(f.iloc[:cut_at])
        if held is not None and len(held):
            yield from settled(held)

    return run


def same(vector: Column) -> list[Column]:
    """128 bits in place of the vector itself, equal for equal vectors as grouping has them (0 equals -0)."""
    return [F.xxhash64(F.lit(seed), vector).alias(f"same{seed}") for seed in (1, 2)]


def vector_links(classes: DataFrame, least: float = 0.93, sample: int = SAMPLE) -> tuple[DataFrame, DataFrame]:
    """``classes``: (cid, label, vector, copies). Returns (cid, n_links to other classes) and forest links (a, b)."""
    spark = classes.sparkSession
    sizes = classes.groupBy("label", F.size("vector").alias("dim")).agg(F.count(F.lit(1)).alias("n")).groupBy("dim").agg(F.sum("n").alias("n"), F.max("n").alias("most")).collect()
    share = min(1.0, 1.5 * sample / max(sum(r["n"] for r in sizes), 1))
    hashed = classes.select("vector", F.xxhash64("vector").alias("h")).filter(F.pmod("h", F.lit(1 << 20)) <= int(share * (1 << 20)))
    by_dim: dict[int, list] = {}
    for r in hashed.orderBy(F.pmod("h", F.lit(1 << 20)), "h", "vector").limit(sample).collect():
        by_dim.setdefault(len(r["vector"]), []).append(r["vector"])
    books = {r["dim"]: fit_index(unit_rows(by_dim[r["dim"]]) if r["dim"] in by_dim else np.eye(1, r["dim"]), r["most"], least) for r in sizes}
    kinds = {f.name: f.dataType.simpleString() for f in classes.schema.fields}
    held = spark.sparkContext.broadcast(books)  # codes are bounded by CODES, so this has a fixed size

    def place(frames):
        yield from _placed(held.value)(frames)

    # found twice, for the counts and for the meetings, which costs less than to store every vector once more
    placed = classes.select("cid", "label", "copies", "vector").mapInPandas(place, f"cid long, label {kinds['label']}, copies long, vector {kinds['vector']}, dim int, cells array<int>")
    keys = ["label", "dim", "cell"]
    crowded = placed.select("label", "dim", F.explode("cells").alias("cell")).groupBy(*keys).agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > CHUNK)
    crowded = cut(crowded.select(*keys, F.ceil(F.col("n") / CHUNK).cast("int").alias("chunks")))
    few = crowded.count() <= BROADCAST_CELLS
    spread = placed.select("cid", "label", "dim", "copies", "vector", F.col("cells")[0].alias("home"), F.posexplode("cells").alias("at", "cell"), "cells")
    dealt = spread.withColumn("visits", F.when(F.col("at") == 0, F.col("cells"))).join(F.broadcast(crowded) if few else crowded, keys, "left")
    paired = dealt.withColumn("chunks", F.coalesce("chunks", F.lit(1))).withColumn("side", F.pmod(F.xxhash64("cid"), F.col("chunks")).cast("int"))
    paired = paired.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1))).withColumn("lo", F.least("side", "other")).withColumn("hi", F.greatest("side", "other"))
    keys += ["lo", "hi"]
    met = cut(paired.select(*keys, "cid", "home", "copies", "visits", "vector", "side").repartition(*keys).sortWithinPartitions(*keys).mapInPandas(_met(least), "a long, b long, n long"))
    return met.filter("n is not null").groupBy(F.col("a").alias("cid")).agg(F.sum("n").alias("n_links")), met.filter("n is null").select("a", "b")


def near_vectors(rows: DataFrame, vec_id: str = "vec_id", vector: str = "embedding", label: str = "label", least: float = 0.93, sample: int = SAMPLE) -> DataFrame:
    """``vec_id``, ``n_links``, ``component_id``, ``kept`` for every row."""
    own = rows.select(F.col(f"`{vec_id}`").alias("vec_id"), F.col(f"`{vector}`").alias("vector"), F.col(f"`{label}`").alias("label")).withColumn("ok", usable(F.col("vector"), F.col("label")))
    good = own.filter("ok")
    classes = cut(good.groupBy("label", "vector").agg(F.min("vec_id").alias("first"), F.count(F.lit(1)).alias("copies"))).withColumn("cid", F.monotonically_increasing_id())
    links, edges = vector_links(classes, least, sample)
    stars = cut(components(edges))
    few = classes.select("cid", "first", "copies", "label", *same(F.col("vector")))
    rooted = few.join(stars, F.col("cid") == F.col("node"), "left").select("cid", "first", "copies", "label", "same1", "same2", F.coalesce("root", "cid").alias("root"))
    lowest = rooted.groupBy("root").agg(F.min("first").alias("component_id"))
    told = rooted.join(lowest, "root").join(links, "cid", "left").select("label", "same1", "same2", "component_id", (F.coalesce("n_links", F.lit(0)) + F.col("copies") - 1).cast("long").alias("n_links"))
    linked = good.select("vec_id", "label", *same(F.col("vector"))).join(told, ["label", "same1", "same2"]).select("vec_id", "n_links", "component_id", F.col("vec_id").eqNullSafe(F.col("component_id")).alias("kept"))
    return linked.unionByName(own.filter("not ok").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"), F.lit(True).alias("kept")))
