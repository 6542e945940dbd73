"""Nearest neighbours by cosine with one vantage-point tree per shard.

Vectors go to the nearest of a bounded sample of pivots (``PIVOTS`` at most, the smallest hashes of the vectors), which
makes cells; a cell of more than ``SHARD_ROWS`` vectors is dealt into several shards. Each shard builds a tree over
unit vectors, where the chord distance orders like the cosine. A query first searches the shards of its own
cell, which gives it a radius, and then only those cells that its ball can meet by the triangle inequality: from the
cell's nearest and farthest distance to its pivot, and from the bisector of two pivots. In a tree, the side of a
vantage point that the inequality excludes is skipped. In both the radius is divided by ``relax``: 1 keeps the search
exact, larger factors skip more. Candidates are scored in double precision on the original vectors; every vector
whose chord is within rounding of the last place is scored, so ties are decided by score and id alone.

Equal vectors are merged to their k + 1 smallest ids before anything is dealt, and equal queries are searched once: a
vector that very many rows have costs one comparison.

Defined results: vectors that are null, zero, or hold a null or non-finite component take no part, as query or
as candidate; vectors meet only vectors of their own length; equal scores rank by smaller id; rows equal in id and
vector count once, other rows that repeat an id are candidates of their own but none of them for queries of that id;
with fewer than k candidates all are returned; rows with a null id take no part; an empty table gives an empty result; further columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window as W, functions as F

from .common import cut, require_columns, shuffle_width, trimmed

LEAF = 128
SLACK = 8  # candidates kept beyond those asked for, so that rounding can't decide who is scored exactly
SHARD_ROWS = 100_000
PIVOTS = 1024
BLOCK = 512
TIE = 1e-6  # chords closer than this may be equal scores


def scaled(rows: np.ndarray) -> np.ndarray:
    """Rows times a power of two each, so that no square is too large or too small; the cosine keeps every bit."""
    return np.ldexp(rows, -np.frexp(np.abs(rows).max(axis=1))[1][:, None])


def unit_rows(rows: np.ndarray) -> np.ndarray:
    rows = scaled(rows)
    return rows / np.sqrt((rows**2).sum(axis=1))[:, None]


class VantageTree:
    """Arrays of a tree over unit vectors: inner nodes hold a vantage point and the median distance to it."""

    def __init__(self, unit: np.ndarray, seed: int = 3):
        self.unit, rng = unit, np.random.default_rng(seed)
        self.nodes: list[tuple] = []
        queue: list[tuple[np.ndarray, int, int]] = [(np.arange(len(unit)), -1, 0)]
        while queue:
            rows, parent, side = queue.pop()
            number = len(self.nodes)
            if parent >= 0:
                self.nodes[parent][2 + side] = number
            if len(rows) <= LEAF:
                self.nodes.append([rows, None, None, None])
                continue
            point = int(rows[rng.integers(len(rows))])
            away = self.chord(unit[point], unit[rows])
            middle = float(np.median(away))
            inner = away <= middle
            if inner.all():
                self.nodes.append([rows, None, None, None])
                continue
            self.nodes.append([point, middle, None, None])
            queue += [(rows[inner], number, 0), (rows[~inner], number, 1)]

    @staticmethod
    def chord(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.sqrt(np.maximum(0.0, 2.0 - 2.0 * (b @ a)))

    def search(self, queries: np.ndarray, keep: int, relax: float = 1.0, within: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(rows, visited): the ``keep`` nearest rows of each query (-1: none) and how many vectors it was compared with.

        within: a distance per query beyond which nothing is looked for."""
        n = len(queries)
        self.best = np.full((n, keep), np.inf)
        self.found = np.full((n, keep), -1, dtype=np.int64)
        self.visited = np.zeros(n, dtype=np.int64)
        self.within = np.full(n, np.inf) if within is None else within
        if self.nodes:
            self._visit(0, np.arange(n), queries, keep, relax)
        return self.found, self.visited

    def _visit(self, number: int, who: np.ndarray, queries: np.ndarray, keep: int, relax: float) -> None:
        if not len(who):
            return
        at, middle, inner, outer = self.nodes[number]
        if middle is None:
            away = np.sqrt(np.maximum(0.0, 2.0 - 2.0 * (queries[who] @ self.unit[at].T)))
            self.visited[who] += len(at)
            away = np.concatenate([self.best[who], away], axis=1)
            rows = np.concatenate([self.found[who], np.broadcast_to(at, (len(who), len(at)))], axis=1)
            pick = np.argpartition(away, keep - 1, axis=1)[:, :keep]
            self.best[who], self.found[who] = np.take_along_axis(away, pick, 1), np.take_along_axis(rows, pick, 1)
            return
        away = np.sqrt(np.maximum(0.0, 2.0 - 2.0 * (queries[who] @ self.unit[at])))
        self.visited[who] += 1
        near = away <= middle
        gap = np.abs(away - middle)
        for side, first, second in ((near, inner, outer), (~near, outer, inner)):
            some, slit = who[side], gap[side]
            self._visit(first, some, queries, keep, relax)
            radius = np.minimum(self.best[some].max(axis=1), self.within[some]) / relax + 1e-7  # the root of a rounding error
            self._visit(second, some[slit <= radius], queries, keep, relax)


def cosine(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Row by row in double precision, components summed in order."""
    if not len(x):
        return np.empty(0)
    x, y = scaled(x), scaled(y)
    dot, xx, yy = np.zeros(len(x)), np.zeros(len(x)), np.zeros(len(x))
    for j in range(x.shape[1]):
        a, b = x[:, j], y[:, j]
        dot, xx, yy = dot + a * b, xx + a * a, yy + b * b
    return np.clip(dot / np.sqrt(xx * yy), -1.0, 1.0)


class Shard:
    """Rows (number, vector) under a tree over their distinct vectors."""

    def __init__(self, numbers: np.ndarray, vectors: np.ndarray, k: int):
        self.numbers, self.vectors, self.k = numbers, vectors, k
        distinct, group = np.unique(vectors, axis=0, return_inverse=True)
        group = group.ravel()
        self.members = np.argsort(group, kind="stable")
        self.first = np.concatenate([[0], np.cumsum(np.bincount(group, minlength=len(distinct)))])
        self.unit = unit_rows(distinct)
        self.tree = VantageTree(self.unit)

    def tied(self, unit: np.ndarray, groups: np.ndarray, away: np.ndarray) -> np.ndarray:
        """groups, or all groups up to the k-th distance and TIE where those found may not hold all of these."""
        if len(groups) < self.k + SLACK:
            return groups
        last = np.sort(away)[self.k - 1] + TIE
        return groups if away.max() > last else np.flatnonzero(VantageTree.chord(unit, self.unit) <= last)

    def answer(self, vectors: np.ndarray, relax: float, within: np.ndarray):
        """(query's place, row's number, score) of the k best rows of every query."""
        unit = unit_rows(vectors)
        found, _ = self.tree.search(unit, self.k + SLACK, relax, within)
        q, r = [], []
        for i, groups in enumerate(found):
            for g in self.tied(unit[i], groups[groups >= 0], self.tree.best[i][groups >= 0]):
                rows = self.members[self.first[g] : self.first[g + 1]]
                q.append(np.full(len(rows), i))
                r.append(rows)
        q, r = (np.concatenate(x).astype(np.int64) if x else np.empty(0, dtype=np.int64) for x in (q, r))
        score = cosine(vectors[q], self.vectors[r])
        order = np.lexsort((self.numbers[r], -score, q))
        q, r, score = q[order], r[order], score[order]
        top = np.arange(len(q)) - np.searchsorted(q, q) < self.k
        return q[top], self.numbers[r[top]], score[top]


def usable(vector) -> F.Column:
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return vector.isNotNull() & ~bad & F.exists(vector, lambda x: x != 0)


def _blocks(batches):
    """(dim, other columns of one dim, vectors as a matrix) of rows (dim, ..., v) that are sorted by dim."""
    for batch in batches:
        if batch.num_rows:
            dims = batch.column(0).to_numpy()
            cuts = [0, *(np.flatnonzero(np.diff(dims)) + 1).tolist(), batch.num_rows]
            for a, z in zip(cuts, cuts[1:]):
                piece = batch.slice(a, z - a)
                yield int(dims[a]), piece, piece.column(piece.num_columns - 1).flatten().to_numpy().reshape(z - a, int(dims[a]))


def _celled(pivots: dict[int, np.ndarray]):
    """Adds cell, the number of the nearest pivot, and away, the chord to it."""

    def run(batches):
        for dim, piece, rows in _blocks(batches):
            for i in range(0, len(rows), 4096):
                chords = np.sqrt(np.maximum(0.0, 2.0 - 2.0 * (unit_rows(rows[i : i + 4096]) @ pivots[dim].T)))
                cell = chords.argmin(axis=1)
                part = piece.slice(i, len(cell))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(cell.astype(np.int32)), pa.array(chords[np.arange(len(cell)), cell])], [*part.schema.names, "cell", "away"])

    return run


def _visits(pivots: dict[int, np.ndarray], cells: dict[int, np.ndarray], relax: float):
    """Queries (dim, number, own, radius, v) -> one row for every further cell that the query's ball may meet."""

    def run(batches):
        for dim, piece, rows in _blocks(batches):
            parts, nearest, farthest = cells[dim]
            number, own, radius = (piece.column(i).to_numpy(zero_copy_only=False) for i in (1, 2, 3))
            vectors = piece.column(4)
            for i in range(0, len(rows), 4096):
                chords = np.sqrt(np.maximum(0.0, 2.0 - 2.0 * (unit_rows(rows[i : i + 4096]) @ pivots[dim].T)))
                here = np.arange(len(chords))
                mine = own[i : i + 4096]
                least = np.maximum(np.maximum(chords - farthest, nearest - chords), (chords - chords[here, mine][:, None]) / 2)
                reach = (least <= radius[i : i + 4096][:, None] / relax + TIE) & (parts > 0)
                reach[here, mine] = False
                who, cell = np.nonzero(reach)
                for a in range(0, len(who), 4096):
                    w, c = i + who[a : a + 4096], cell[a : a + 4096]
                    times = parts[c]
                    part = np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
                    w, c = np.repeat(w, times), np.repeat(c, times)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(w), dim, np.int32)), pa.array(c.astype(np.int32)), pa.array(part.astype(np.int32)), pa.array(number[w]), pa.array(radius[w]), vectors.take(pa.array(w))], ["dim", "cell", "part", "number", "radius", "v"])

    return run


def _search(k: int, relax: float):
    """Rows of a shard (kind 0) precede its queries (kind 1): (query, number, score) of the k best."""

    def run(batches):
        key, numbers, parts, tree = None, [], [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            dims, cell, shard, kinds = (batch.column(i).to_numpy() for i in range(4))
            edges = np.flatnonzero((np.diff(dims) != 0) | (np.diff(cell) != 0) | (np.diff(shard) != 0) | (np.diff(kinds) != 0)) + 1
            bounds = [0, *edges.tolist(), batch.num_rows]
            for a, z in zip(bounds, bounds[1:]):
                own = (int(dims[a]), int(cell[a]), int(shard[a]))
                if own != key:
                    key, numbers, parts, tree = own, [], [], None
                piece = batch.slice(a, z - a)
                number, radius = piece.column(4).to_numpy(), piece.column(5).to_numpy()
                block = piece.column(6).flatten().to_numpy().reshape(z - a, own[0])
                if kinds[a] == 0:
                    numbers.append(number)
                    parts.append(block)
                    continue
                if not numbers:
                    continue
                if tree is None:
                    tree = Shard(np.concatenate(numbers), np.concatenate(parts), k)
                for i in range(0, z - a, BLOCK):
                    q, v, s = tree.answer(block[i : i + BLOCK], relax, radius[i : i + BLOCK])
                    yield pa.RecordBatch.from_arrays([pa.array(number[i : i + BLOCK][q]), pa.array(v), pa.array(s)], ["query", "number", "score"])

    return run


def _searched(members: DataFrame, sent: DataFrame, tasks: int, k: int, relax: float) -> DataFrame:
    """members (dim, cell, part, number, v), sent with radius as well -> query, number, score."""
    columns = ["dim", "cell", "part", "kind", "number", "radius", "v"]
    both = members.withColumns({"kind": F.lit(0), "radius": F.lit(0.0)}).select(*columns).union(sent.withColumn("kind", F.lit(1)).select(*columns))
    dealt = both.repartition(tasks, "dim", "cell", "part").sortWithinPartitions("dim", "cell", "part", "kind")
    return dealt.mapInArrow(trimmed(_search(k, relax)), "query bigint, number bigint, score double")


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 5, relax: float = 1.0, shard_rows: int = SHARD_ROWS, pivots: int = PIVOTS, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score for every usable query."""
    require_columns(vectors, id_col, vector_col)
    if relax < 1 or k < 1:
        raise ValueError("relax and k are 1 or more")
    spark = vectors.sparkSession
    vec = F.col(vector_col).cast("array<double>")
    read = lambda df: df.select(F.col(id_col).cast("long").alias("id"), vec.alias("v")).filter(F.col("id").isNotNull() & usable(F.col("v")))
    ask = k + 1  # one more than asked for: a query's own row is taken out at the end
    # Equal rows merge before they travel, and of equal vectors the window's limit lets few through on either side.
    alike = W.partitionBy("v").orderBy("id")
    distinct = read(vectors).groupBy("v", "id").agg(F.lit(1)).withColumn("at", F.row_number().over(alike)).filter(F.col("at") <= ask)
    base = cut(distinct.select(F.size("v").alias("dim"), "id", "v", (F.col("at") == 1).alias("lead")), "vectors")
    sizes = {r["dim"]: r["n"] for r in base.groupBy("dim").agg(F.count("*").alias("n")).collect()}  # one row per length of vectors
    width = shuffle_width(spark)
    wanted = {d: min(pivots, max(1, width * n // max(1, sum(sizes.values())), n // shard_rows)) for d, n in sizes.items()}
    limit = F.element_at(F.create_map(*[F.lit(x) for d, n in wanted.items() for x in (d, n)]), F.col("dim")) if wanted else F.lit(0)
    drawn = base.filter("lead").withColumn("at", F.row_number().over(W.partitionBy("dim").orderBy(F.xxhash64("v"), "id"))).filter(F.col("at") <= pivots).filter(F.col("at") <= limit)
    points: dict[int, list] = {}
    for r in drawn.select("dim", "v").toLocalIterator():  # pivots of each length
        points.setdefault(r["dim"], []).append(r["v"])
    centres = {d: unit_rows(np.array(v, dtype=np.float64)) for d, v in points.items()}

    placed = cut(base.select("dim", F.col("id").alias("number"), "v").mapInArrow(trimmed(_celled(centres)), "dim int, number bigint, v array<double>, cell int, away double"), "cells")
    cells = {d: (np.zeros(len(c), np.int64), np.zeros(len(c)), np.full(len(c), -1.0)) for d, c in centres.items()}
    for r in placed.groupBy("dim", "cell").agg(F.count("*").alias("n"), F.min("away").alias("lo"), F.max("away").alias("hi")).toLocalIterator():  # one row per pivot
        own = cells[r["dim"]]
        own[0][r["cell"]], own[1][r["cell"]], own[2][r["cell"]] = -(-r["n"] // shard_rows), r["lo"], r["hi"]
    shards = int(sum(own[0].sum() for own in cells.values()))
    tasks = max(1, min(shards, 4 * width) if shards <= 4 * width else shards // 4)
    split = [F.lit(x) for d, own in cells.items() for c, n in enumerate(own[0].tolist()) if n > 1 for x in (f"{d}:{c}", n)]  # cells of several shards only
    several = F.coalesce(F.element_at(F.create_map(*split), F.concat("dim", F.lit(":"), "cell")), F.lit(1)) if split else F.lit(1)
    # Equal vectors share a shard.
    members = placed.withColumn("part", F.pmod(F.xxhash64("v"), several).cast("int")).select("dim", "cell", "part", "number", "v")

    asked = read(queries).select(F.size("v").alias("dim"), "id", "v")
    once = asked.select("dim", "v").distinct().filter(F.col("dim").isin(list(sizes)) if sizes else F.lit(False))
    once = cut(once.withColumn("number", F.monotonically_increasing_id()), "queries")  # holds for the query from here on
    celled = once.select("dim", "number", "v").mapInArrow(trimmed(_celled(centres)), "dim int, number bigint, v array<double>, cell int, away double")
    celled = cut(celled, "celled-queries")
    parts = F.explode(F.sequence(F.lit(0), several.cast("int") - 1))
    first = celled.select("dim", "cell", parts.alias("part"), "number", F.lit(float("inf")).alias("radius"), "v")
    found = cut(_searched(members, first, tasks, ask, relax), "own-cells")
    best = W.partitionBy("query").orderBy(F.desc("score"), "number")
    last = found.withColumn("at", F.row_number().over(best)).filter(F.col("at") == ask).select(F.col("query").alias("number"), "score")
    chord = F.sqrt(F.greatest(F.lit(0.0), 2 - 2 * F.col("score"))) + F.lit(TIE)
    radius = F.when(F.col("score").isNotNull(), chord).otherwise(float("inf"))  # fewer than asked for so far
    second = celled.join(last, "number", "left").select("dim", "number", "cell", radius.alias("radius"), "v")
    sent = second.mapInArrow(trimmed(_visits(centres, cells, relax)), "dim int, cell int, part int, number bigint, radius double, v array<double>")
    found = found.union(_searched(members, sent, tasks, ask, relax))

    # The k + 1 best of each different query, then for each query's own id the k best others.
    tops = found.withColumn("at", F.row_number().over(best)).filter(F.col("at") <= ask)
    lists = tops.groupBy("query").agg(F.sort_array(F.collect_list(F.struct("at", F.col("number").alias("vec_id"), "score"))).alias("best"))  # k + 1 at most
    full = asked.join(once.join(lists.withColumnRenamed("query", "number"), "number").select("v", "best"), "v")
    others = F.slice(F.filter("best", lambda b: b["vec_id"] != F.col("id")), 1, k)
    return full.select(F.col("id").alias("query_id"), F.posexplode(others).alias("at", "b")).select("query_id", (F.col("at") + 1).cast("int").alias("rank"), "b.vec_id", "b.score")


def search_report(embeddings: DataFrame, every: int = 50) -> DataFrame:
    """The query set is every row whose id is divisible by ``every``; relax 1, so the search is exact."""
    return nearest(embeddings, embeddings.filter(F.col("vec_id") % every == 0))


ORACLE = """
WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_cosine_similarity(q.e, c.e) AS score FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.e) = len(c.e) WHERE q.vec_id % 50 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 5
"""
