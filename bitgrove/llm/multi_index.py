"""Embedding near-dedup with an inverted multi-index.

Two codebooks, one per half of the vectors, span a grid of cells; every vector lies in the cell of its nearest codewords. A
vector visits cells in the order of a bound on how far a near vector in that cell must be: per half, the distance to the plane
between its own codeword and the cell's. The traversal stops at the radius at which the target recall is reached on a bounded
sample of vectors moved to exactly the least cosine. All pairs met in a cell are verified in double precision. Equal vectors
are one from the start. Cells with many vectors are split, and a task reports counts and a spanning star, never all pairs.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored
from .components import components

#: Vectors that codebooks and the radius are fitted on, at most; home vectors of a cell that one task holds.
SAMPLE, HOMES = 20_000, 2_000
#: Vectors of a cell, about; codewords of a half, at most; vectors of one length from which on they get a grid of their own.
CELL, WORDS, ENOUGH = 48, 2_048, 1_000


def codebook(x: np.ndarray, k: int, rng, rounds: int = 8) -> np.ndarray:
    """k-means on a sample."""
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        own = ((c**2).sum(1)[None, :] - 2 * x @ c.T).argmin(1)
        n = np.bincount(own, minlength=len(c))
        sums = np.zeros_like(c)
        np.add.at(sums, own, x)
        c[n > 0] = sums[n > 0] / n[n > 0, None]
    return np.unique(c, axis=0)


class Grid:
    """Codebooks of both halves and the radius of the traversal."""

    def __init__(self, books: list[np.ndarray], radius: float):
        self.books, self.radius = books, radius
        self.half = books[0].shape[1]
        self.gaps = [np.sqrt(np.maximum(((b[:, None] - b[None]) ** 2).sum(2), 1e-18)) for b in books]

    def bounds(self, x: np.ndarray):
        """Own codeword and squared distance to each codeword's region, per half."""
        out = []
        for part, book, gap in zip((x[:, : self.half], x[:, self.half :]), self.books, self.gaps, strict=True):
            d = (part**2).sum(1)[:, None] + (book**2).sum(1)[None] - 2 * part @ book.T
            own = d.argmin(1)
            far = np.maximum(d - d[np.arange(len(d)), own][:, None], 0) / (2 * gap[own])
            far[np.arange(len(d)), own] = 0
            out.append((own, far**2))
        return out

    def home(self, x: np.ndarray) -> np.ndarray:
        (a, _), (b, _) = self.bounds(x)
        return a * len(self.books[1]) + b

    def visits(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Cells visited, nearest first for each vector: (vector numbers, cells)."""
        (_, fa), (_, fb) = self.bounds(x)
        rows, cells = [], []
        width = len(self.books[1])
        for i in range(len(x)):
            # Both halves in order of distance: each step along the first admits a shorter run of the second.
            ia, ib = np.flatnonzero(fa[i] <= self.radius), np.flatnonzero(fb[i] <= self.radius)
            ia, ib = ia[np.argsort(fa[i][ia], kind="stable")], ib[np.argsort(fb[i][ib], kind="stable")]
            a, b = fa[i][ia], fb[i][ib]
            n = np.searchsorted(b, self.radius - a, "right")
            p = np.repeat(np.arange(len(a)), n)
            q = np.arange(len(p)) - np.repeat(np.cumsum(n) - n, n)
            order = np.argsort(a[p] + b[q], kind="stable")
            cells.append((ia[p] * width + ib[q])[order])
            rows.append(np.full(len(p), i))
        return np.concatenate(rows), np.concatenate(cells)

    def reaches(self, x: np.ndarray, cells: np.ndarray) -> np.ndarray:
        """Whether each vector visits its cell."""
        (_, fa), (_, fb) = self.bounds(x)
        i = np.arange(len(x))
        return fb[i, cells % len(self.books[1])] <= self.radius - fa[i, cells // len(self.books[1])]


def fitted(x: np.ndarray, total: int, least: float, recall: float) -> Grid:
    """A grid whose cells hold about CELL of all vectors, and the radius that keeps the target recall on moved vectors."""
    rng = np.random.default_rng(5)
    half = (x.shape[1] + 1) // 2
    k = min(WORDS, max(2, round(math.sqrt(total / CELL))), len(x))
    grid = Grid([codebook(x[:, :half], k, rng), codebook(x[:, half:], k, rng)], 2 * (1 - least))
    y = x[rng.permutation(len(x))[:4000]]
    move = rng.normal(size=y.shape)
    move -= (move * y).sum(1)[:, None] * y
    move /= np.maximum(np.linalg.norm(move, axis=1), 1e-12)[:, None]
    near = least * y + math.sqrt(1 - least**2) * move
    (_, fa), (_, fb) = grid.bounds(near)
    (a, _), (b, _) = grid.bounds(y)
    i = np.arange(len(y))
    grid.radius = min(grid.radius, float(np.quantile(fa[i, a] + fb[i, b], recall)) + 1e-12)
    return grid


def _matrix(column: pa.ChunkedArray | pa.Array, dim: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    x = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def near_vectors(rows: DataFrame, least: float = 0.95, recall: float = 0.995) -> DataFrame:
    """vec_id, n_links, component_id, kept for each row of rows (vec_id, embedding).

    Vectors that are null, empty, zero, or hold null or non-finite components link with nothing; vectors of different lengths
    do not link, and each length of ENOUGH vectors has a grid of its own; equal vectors always link; rows that share a vec_id
    are vectors of their own that count as one node; rows without one link with nothing and are kept. Other columns are ignored.
    An empty table gives no row.
    """
    base = rows.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"))
    fine = F.col("v").isNotNull() & (F.size("v") > 0) & ~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists("v", lambda x: x != 0)
    base = stored(base.withColumn("v", F.when(fine, F.transform("v", lambda x: x + F.lit(0.0)))).withColumn("k", F.when(F.col("v").isNotNull(), F.sha2(F.array_join("v", ","), 256))), "vectors")
    reps = stored(base.filter("v is not null and vec_id is not null").groupBy("k").agg(F.min("vec_id").alias("rep"), F.count("*").alias("n"), F.first("v").alias("v")).withColumn("dim", F.size("v")), "distinct")
    edges = _edges(reps, _grids(reps, least, recall), least)
    total = edges.groupBy("k").agg(F.sum("n_links").alias("near"))
    parts = components(edges.filter("star is not null").select(F.col("rep").alias("a"), F.col("star").alias("b")))
    found = reps.select("k", "rep", "n").join(total, "k", "left").join(parts.withColumnRenamed("id", "rep"), "rep", "left")
    found = found.select("k", (F.coalesce("near", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component_id", "rep").alias("component_id"))
    named = F.when(F.col("vec_id").isNotNull(), F.col("k")).alias("k")
    out = base.select("vec_id", named).join(found, "k", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def _grids(reps: DataFrame, least: float, recall: float) -> dict[int, Grid]:
    """A grid for each length that enough vectors have, fitted on a bounded sample of them. Vectors of other lengths lie in one
    cell per length, which is compared whole."""
    out = {}
    for row in reps.groupBy("dim").count().filter(F.col("count") >= ENOUGH).collect():
        few = reps.filter(F.col("dim") == row["dim"]).orderBy("k").limit(SAMPLE).select("v").toArrow()["v"]
        out[row["dim"]] = fitted(_matrix(few, row["dim"]), row["count"], least, recall)
    return out


def _edges(reps: DataFrame, grids: dict[int, Grid], least: float) -> DataFrame:
    """k, rep, n_links (weighted), star (a smaller vector of the same group of links, or null) of distinct vectors."""
    names = ["k", "rep", "n", "v", "dim"]

    def visit(batches):
        for batch in batches:
            dims = batch.column(4).to_numpy(zero_copy_only=False)
            for dim in np.unique(dims).tolist():
                same = batch.take(pa.array(np.flatnonzero(dims == dim)))
                for at in range(0, same.num_rows, 1000):
                    part = same.slice(at, 1000)
                    home = i = cells = np.zeros(part.num_rows, np.int64)
                    i = np.arange(len(home))
                    if grid := grids.get(dim):
                        x = _matrix(part.column(3), dim)
                        home = grid.home(x)
                        to, reached = grid.visits(x)
                        away = reached != home[to]
                        i, cells = np.concatenate([i, to[away]]), np.concatenate([home, reached[away]])
                    yield pa.RecordBatch.from_arrays([pa.array(cells), pa.array(home[i]), *(part.column(c).take(pa.array(i)) for c in range(5))], names=["cell", "home", *names])

    dealt = stored(reps.select(*names).mapInArrow(visit, "cell long, home long, k string, rep long, n long, v array<double>, dim int"), "visits")
    crowd = dealt.filter("cell = home").groupBy("dim", "cell").agg(F.ceil(F.count("*") / HOMES).cast("int").alias("parts"))
    blocks = F.sequence(F.lit(0), F.col("parts") - 1)
    own = F.pmod(F.xxhash64("k"), F.col("parts")).cast("int")
    spread = dealt.join(crowd, ["dim", "cell"]).withColumn("own", F.when(F.col("cell") == F.col("home"), own)).withColumn("part", F.explode(blocks))

    def meet(table: pa.Table) -> pa.Table:
        dim, cell, part = (table[c][0].as_py() for c in ("dim", "cell", "part"))
        x = _matrix(table["v"], dim)
        rep, home, n = (table[c].to_numpy() for c in ("rep", "home", "n"))
        held = table["own"].fill_null(-1).to_numpy() == part
        inside = np.flatnonzero(held)
        links, star = np.zeros(len(x), np.int64), np.arange(len(x))

        def root(i):
            while star[i] != i:
                star[i] = star[star[i]]
                i = star[i]
            return i

        for at in range(0, len(x), 512):
            rows = np.arange(at, min(at + 512, len(x)))
            i, j = np.nonzero(x[rows] @ x[inside].T >= least)
            i, j = rows[i], inside[j]
            same = home[i] == cell
            once = same & (rep[i] < rep[j]) | ~same
            i, j = i[once], j[once]
            # A pair in two cells that visit each other's is counted in the later cell.
            twice = home[i] > home[j]
            if twice.any():
                t = np.flatnonzero(twice)
                drop = t[grids[dim].reaches(x[j[t]], home[i[t]])]
                keep = np.ones(len(i), bool)
                keep[drop] = False
                i, j = i[keep], j[keep]
            np.add.at(links, i, n[j])
            np.add.at(links, j, n[i])
            for p, q in zip(i.tolist(), j.tolist(), strict=True):
                p, q = root(p), root(q)
                if p != q:
                    star[max(p, q, key=lambda z: rep[z])] = min(p, q, key=lambda z: rep[z])
        hit = np.flatnonzero(links)
        top = np.array([root(int(i)) for i in hit], np.int64)
        return pa.table({"k": table["k"].take(pa.array(hit)), "rep": rep[hit], "n_links": links[hit], "star": pa.array(rep[top], mask=rep[top] == rep[hit]) if len(hit) else pa.array([], pa.int64())})

    return stored(spread.groupBy("dim", "cell", "part").applyInArrow(meet, "k string, rep long, n_links long, star long"), "near")
