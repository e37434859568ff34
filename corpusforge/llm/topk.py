"""Exact top-k by inner product with cover trees over queries and data.

1. Vectors become integers floor(scale * x). At most MAX_CELLS pivots, chosen farthest-first from a
   sample of bounded size, cut space into cells; every vector goes to its nearest pivot's cell, and a
   cell of more than `block_rows` rows is dealt into parts by hash. Radius and greatest length of each
   cell are taken over all its rows.
2. Each query first meets the part that it stands in; that gives it a first kth score.
3. It is then sent to those cells only whose bound <q,p> + |q| r (and |q| times the greatest length)
   reaches that score. Data are copied for each group of `query_group` queries that asks for their part.
4. Where queries and a part meet, both are indexed by cover trees: farthest-first centres, each node's
   members within its covering radius, radii halved from level to level or as far as FANOUT children
   allow. A pair of nodes (Q, P) is skipped when even <q,p> + |q| r_P + |p| r_Q + r_Q r_P is below the
   worst kth score among Q's queries. Leaves multiply the first components, and finish only those
   products that Cauchy and Schwarz's bound on the rest leaves a chance.
5. A window keeps the best k of all parts.

What covering radii can skip depends on the data: with vectors spread evenly over a sphere of many
dimensions all nodes overlap and only the leaves' bound saves work (`Work` counts both).

Equal vectors are one point of the tree with their 2k smallest ids, at most k of each id: more can
never be among the k best, ties going to the smaller id; so a vector that fills a third of the rows
costs one point a part.

Edge cases: vectors that are null or hold null or non-finite components take no part, as data or as
query; shorter vectors count as padded with zeros; rows with a null id are data (last among equal
scores) and never queries; repeated rows are found as often as they occur; a repeated query id asks
once, with its smallest vector, and ignores every row of its own id; components and scores beyond 64
bits count as the greatest or smallest 64-bit number; vectors of any length are held a block at a time;
with fewer rows than k all are returned; an empty table gives no rows; further columns don't matter.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .shared import landed

RESULT = "query_id long, vec_id long, score long"
LEAF, QUERY_LEAF, FANOUT = 32, 8, 16
#: Points of the first and of the largest run of leaves that are multiplied together.
FIRST_RUN, LARGEST_RUN = 128, 8192
#: Most pivots, most numbers in all pivots together, sampled rows per pivot.
MAX_CELLS, MAX_NUMBERS, SAMPLED = 4096, 1 << 22, 4
LEAST, MOST = -(1 << 63), (1 << 63) - 1
NO_ID = 1 << 63  # a null id: after all others


def _matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """Lists of longs to a matrix, zero-padded."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    lengths = pa.compute.list_value_length(column).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = column.flatten().to_numpy(zero_copy_only=False)
    width = int(lengths.max(initial=0))
    out = np.zeros((len(lengths), width), np.int64)
    if width:
        out[np.arange(width) < lengths[:, None]] = flat
    return out


def _wide(m: np.ndarray, width: int) -> np.ndarray:
    return np.pad(m, ((0, 0), (0, max(0, width - m.shape[1]))))


def numeric(*parts: np.ndarray) -> type:
    """float64 if all inner products are exact in it, else int64, else Python integers."""
    width = max(p.shape[1] for p in parts)
    most = max([max(-int(p.min()), int(p.max())) for p in parts if p.size], default=0)
    bound = most * most * max(width, 1)
    return np.float64 if bound < 1 << 52 else np.int64 if bound < 1 << 62 else object


def spread_centres(x: np.ndarray, first: int, dist: np.ndarray, most: int, reach: float) -> tuple[list[int], np.ndarray, np.ndarray]:
    """Rows of x farthest from all before, until `most` or until all are within `reach`; each row's nearest and its distance."""
    centres, near, d = [first], np.zeros(len(x), np.int64), dist
    while len(centres) < most and d.max() > reach:
        new = int(d.argmax())
        there = np.sqrt(((x - x[new]) ** 2).sum(1))
        closer = there < d
        near[closer] = len(centres)
        d = np.where(closer, there, d)
        centres.append(new)
    return centres, near, d


class CoverTree:
    """Nodes with centre, covering radius, greatest length and children."""

    def __init__(self, points: np.ndarray, leaf: int = LEAF):
        self.x = points.astype(np.float64)
        self.norm = np.sqrt((self.x * self.x).sum(1))
        self.center, self.radius, self.longest, self.children, self.points = [], [], [], [], []
        stack = []
        if len(points):
            every = np.arange(len(points))
            stack.append((0, every, np.sqrt(((self.x - self.x[0]) ** 2).sum(1)), -1))
        while stack:
            c, members, dist, parent = stack.pop()
            me = len(self.center)
            self.center.append(c)
            # A hair above the largest distance, so that rounding can't hide a point.
            self.radius.append(float(dist.max()) * (1 + 1e-9))
            self.longest.append(float(self.norm[members].max()) * (1 + 1e-9))
            self.children.append([])
            self.points.append(members)
            if parent >= 0:
                self.children[parent].append(me)
            if len(members) <= leaf or self.radius[me] == 0:
                continue
            own = int(np.nonzero(members == c)[0][0])
            centres, near, d = spread_centres(self.x[members], own, dist, FANOUT, self.radius[me] / 2)
            for i, at in enumerate(centres):
                inside = near == i
                stack.append((int(members[at]), members[inside], d[inside], me))


@dataclass
class Work:
    """What a search did, out of `pairs` inner products: products in leaves that met, those of them finished, multiplications."""

    pairs: int = 0
    begun: int = 0
    finished: int = 0
    multiplied: int = 0
    width: int = 0

    def shares(self) -> tuple[float, float, float]:
        n = max(1, self.pairs)
        return self.begun / n, self.finished / n, self.multiplied / (n * max(1, self.width))


def dual_tree(queries: np.ndarray, own: list[int], points: np.ndarray, ids: list[list[int]], k: int, floor: np.ndarray | None = None) -> tuple[list[list[tuple[int, int]]], Work]:
    """Per query its k best (score, id) that reach its floor, and what it took.

    own: each query's id, which it may not find; ids: the ids of each (distinct) point, ascending.
    """
    kind, width = numeric(queries, points), points.shape[1]
    qt, pt = CoverTree(queries, QUERY_LEAF), CoverTree(points)
    found: list[list[tuple[int, int]]] = [[] for _ in own]  # (-score, id), best first
    worst = np.full(len(own), -np.inf) if floor is None else floor.astype(np.float64)
    work = Work(pairs=len(queries) * len(points), width=width)
    q, p = queries.astype(kind), points.astype(kind)
    head = width if kind is object else -(-width * 11 // 16)
    tail = lambda t: np.sqrt((t.x[:, head:] ** 2).sum(1)) * (1 + 1e-9)
    q_tail, p_tail = tail(qt), tail(pt)
    qc, pc = qt.x[qt.center], pt.x[pt.center]
    qn, pn = qt.norm[qt.center], pt.norm[pt.center]
    qr, pr, pl = np.array(qt.radius), np.array(pt.radius), np.array(pt.longest)

    kids = np.array([len(x) for x in pt.children])
    begin, kid = np.cumsum(kids) - kids, np.array([c for x in pt.children for c in x], np.int64)
    size = np.array([len(x) for x in pt.points])

    def opened(nodes: np.ndarray) -> np.ndarray:
        n = kids[nodes]
        return kid[np.repeat(begin[nodes] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))]

    def upper(a: int, nodes: np.ndarray) -> np.ndarray:
        most = pc[nodes] @ qc[a] + qn[a] * pr[nodes] + pn[nodes] * qr[a] + qr[a] * pr[nodes]
        most = np.minimum(most, (qn[a] + qr[a]) * pl[nodes])
        return most + 1e-9 * (1 + np.abs(most) + qn[a] * pn[nodes])

    def multiply(rows: np.ndarray, cols: np.ndarray) -> None:
        scores = q[rows][:, :head] @ p[cols][:, :head].T
        work.begun += scores.size
        work.multiplied += scores.size * head
        if kind is object:
            scores = np.clip(scores, LEAST, MOST)
        most = scores.astype(np.float64) + np.outer(q_tail[rows], p_tail[cols])
        alive = most + 1e-9 * np.abs(most) + 1 >= worst[rows, None]
        i, j = np.nonzero(alive)
        score = scores[i, j]
        if head < width:
            score = score + (q[rows[i], head:] * p[cols[j], head:]).sum(1)
            work.multiplied += len(i) * (width - head)
        work.finished += len(i)
        # Few reach the worst kth score; only their queries are gone through.
        good = score.astype(np.float64) >= worst[rows[i]]
        i, j, score = i[good], j[good], score[good]
        for at in np.split(np.arange(len(i)), np.nonzero(np.diff(i))[0] + 1) if len(i) else ():
            row, s, c = int(rows[i[at[0]]]), score[at], cols[j[at]]
            places = k + hides[row]
            if kind is not object and len(s) > places:  # equal scores of the last place all stay
                keep = s >= np.partition(s, len(s) - places)[len(s) - places]
                s, c = s[keep], c[keep]
            have = found[row]
            for x, y in zip(s.tolist(), c.tolist()):
                have += [(-int(x), v) for v in ids[y] if v != own[row]][:k]
            have.sort()
            del have[k:]
            if len(have) == k:
                worst[row] = max(worst[row], float(-have[-1][0]))

    # At how many points a query's own id stands alone, and so may take a place without filling it.
    alone: dict[int, int] = {}
    for x in ids:
        if x and x[0] == x[-1]:
            alone[x[0]] = alone.get(x[0], 0) + 1
    hides = [alone.get(o, 0) for o in own]

    stack = [(0, np.zeros(1, np.int64))] if len(queries) and len(points) else []
    while stack:
        a, nodes = stack.pop()
        rows = qt.points[a]
        nodes = nodes[upper(a, nodes) >= worst[rows].min()]
        if qt.children[a]:
            # The larger side opens first.
            wide = (kids[nodes] > 0) & (pr[nodes] >= qr[a])
            there = np.concatenate([nodes[~wide], opened(nodes[wide])])
            stack += [(c, there) for c in qt.children[a]]
            continue
        while (kids[nodes] > 0).any():
            inner = kids[nodes] > 0
            below = opened(nodes[inner])
            nodes = np.concatenate([nodes[~inner], below[upper(a, below) >= worst[rows].min()]])
        # The most promising leaves first, in ever longer runs; each run meets the scores that the last one left.
        most = upper(a, nodes)
        order = np.argsort(-most)
        nodes, most, run = nodes[order], most[order], FIRST_RUN
        while len(nodes) and most[0] >= worst[rows].min():
            upto = max(1, int(np.searchsorted(np.cumsum(size[nodes]), run, "right")))
            upto = min(upto, int(np.searchsorted(-most, -worst[rows].min(), "right")))
            multiply(rows, np.concatenate([pt.points[n] for n in nodes[:upto].tolist()]))
            nodes, most, run = nodes[upto:], most[upto:], min(LARGEST_RUN, 4 * run)
    return [[(-s, v) for s, v in f] for f in found], work


def points_of(keys: list[int], vectors: np.ndarray, k: int) -> tuple[np.ndarray, list[list[int]]]:
    """Distinct vectors, and of each the 2k smallest ids, at most k of one id."""
    points, where = np.unique(vectors, axis=0, return_inverse=True)
    ids: list[list[int]] = [[] for _ in points]
    for key, at in sorted(zip(keys, where.ravel().tolist())):
        have = ids[at]
        if len(have) < 2 * k and not (len(have) >= k and have[-k] == key):
            have.append(key)
    return points, ids


def _search(data: pa.Table, queries: pa.Table, k: int) -> pa.Table:
    rows = []
    if data.num_rows and queries.num_rows:
        mine, asked = _matrix(data.column("x")), _matrix(queries.column("x"))
        width = max(mine.shape[1], asked.shape[1], 1)
        points, ids = points_of([NO_ID if v is None else v for v in data.column("vec_id").to_pylist()], _wide(mine, width), k)
        own = queries.column("vec_id").to_pylist()
        kth = queries.column("kth").to_numpy(zero_copy_only=False).astype(np.float64)
        best, _ = dual_tree(_wide(asked, width), own, points, ids, k, np.where(np.isnan(kth), -np.inf, kth))
        rows = [(o, None if v == NO_ID else v, s) for o, b in zip(own, best) for s, v in b]
    cols = list(zip(*rows)) if rows else [[], [], []]
    return pa.Table.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["query_id", "vec_id", "score"])


def fit_pivots(v: DataFrame, rows: int, block_rows: int, least_blocks: int) -> np.ndarray:
    """Pivots from a bounded sample: the rows with the smallest hashes, then farthest-first among them."""
    cells = min(MAX_CELLS, max(least_blocks, -(-rows // block_rows)))
    width = v.agg(F.max(F.size("x"))).first()[0] or 1
    cells = max(1, min(cells, MAX_NUMBERS // (SAMPLED * width)))
    sample = v.select("x", F.xxhash64("vec_id", "x").alias("h")).orderBy("h").limit(cells * SAMPLED).select("x").collect()
    x = np.zeros((len(sample), width))
    for i, r in enumerate(sample):
        x[i, : len(r[0])] = r[0]
    if not len(x):
        return x
    centres, _, _ = spread_centres(x, 0, np.sqrt(((x - x[0]) ** 2).sum(1)), cells, 0.0)
    return x[centres]


def _placed(v: DataFrame, pivots: np.ndarray) -> DataFrame:
    """v with cell, distance to its pivot and length; pivots travel with the tasks (MAX_NUMBERS at most)."""
    square = (pivots * pivots).sum(1)

    def run(batches):
        for b in batches:
            x = _matrix(b.column(1)).astype(np.float64) if b.num_rows else np.zeros((0, 1))
            x = _wide(x, pivots.shape[1])
            cell = (square - 2 * (x @ pivots.T)).argmin(1).astype(np.int32) if len(x) else np.zeros(0, np.int32)
            dist, length = np.sqrt(((x - pivots[cell]) ** 2).sum(1)), np.sqrt((x * x).sum(1))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(cell), pa.array(dist), pa.array(length)], names=["vec_id", "x", "cell", "dist", "length"])

    return v.mapInArrow(run, "vec_id long, x array<long>, cell int, dist double, length double")


def _routed(queries: DataFrame, pivots: np.ndarray, cells: dict[int, tuple[float, float]]) -> DataFrame:
    """queries with `cells`: those whose bound reaches the query's kth score."""
    names = np.array(sorted(cells), np.int32)
    radius, longest = (np.array([cells[c][i] for c in names.tolist()]) * (1 + 1e-9) for i in (0, 1))
    centres = pivots[names]

    def run(batches):
        for b in batches:
            x = _wide(_matrix(b.column("x")).astype(np.float64), centres.shape[1]) if b.num_rows else np.zeros((0, centres.shape[1]))
            n = np.sqrt((x * x).sum(1))[:, None]
            most = np.minimum(x @ centres.T + n * radius, n * longest)
            kth = b.column("kth").to_numpy(zero_copy_only=False).astype(np.float64)[:, None]
            there = ~(most + 1e-9 * (1 + np.abs(most) + n * longest) < kth)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([names[t] for t in there], pa.list_(pa.int32()))], names=[*b.schema.names, "cells"])

    return queries.mapInArrow(run, "vec_id long, x array<long>, kth long, own_cell int, own_part int, cells array<int>")


def top_k(vectors: DataFrame, is_query, *, k: int = 10, scale: int = 1024, vec_id: str = "vec_id", vector: str = "embedding", block_rows: int = 8192, query_group: int = 4096, least_blocks: int = 24) -> DataFrame:
    """query_id, rank, vec_id, score for the rows where is_query(vec_id) holds."""
    v = vectors.select(F.col(vec_id).cast("long").alias("vec_id"), F.col(vector).cast("array<double>").alias("x")).where("x is not null")
    v = v.where(F.forall("x", lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < float("inf"))))
    whole = lambda e: F.floor(F.greatest(F.lit(float(LEAST)), F.least(F.lit(float(MOST - 1023)), e * float(scale))))
    v = v.select("vec_id", F.transform("x", lambda e: whole(e).cast("long")).alias("x"))
    rows, asked = v.agg(F.count(F.lit(1)), F.count_if(is_query(F.col("vec_id")))).first()
    pivots = fit_pivots(v, rows, block_rows, least_blocks)
    if not rows:
        pivots = np.zeros((1, 1))
    placed = landed(_placed(v, pivots), "placed")
    stats = placed.groupBy("cell").agg(F.count(F.lit(1)).alias("n"), F.max("dist").alias("dist"), F.max("length").alias("length")).collect()  # MAX_CELLS rows at most
    parts = F.create_map(*[x for r in stats for x in (F.lit(r["cell"]), F.lit(-(-r["n"] // block_rows)))]) if stats else F.create_map(F.lit(0), F.lit(1))
    data = placed.withColumn("part", F.pmod(F.xxhash64("vec_id", "x"), parts[F.col("cell")]).cast("int"))
    mine = data.where(is_query(F.col("vec_id"))).groupBy("vec_id").agg(F.min(F.struct("x", "cell", "part")).alias("q")).select("vec_id", "q.*", F.lit(None).cast("long").alias("kth"))
    search = lambda left, right: _search(left, right, k)
    # Its own part first.
    near = landed(data.select("cell", "part", "vec_id", "x").groupBy("cell", "part").cogroup(mine.groupBy("cell", "part")).applyInArrow(search, RESULT), "near")
    kth = near.groupBy("query_id").agg(F.when(F.count(F.lit(1)) >= k, F.min("score")).alias("kth"))
    known = mine.drop("kth").join(kth, mine["vec_id"] == kth["query_id"], "left").select("vec_id", "x", "kth", F.col("cell").alias("own_cell"), F.col("part").alias("own_part"))
    routed = landed(_routed(known, pivots, {r["cell"]: (r["dist"], r["length"]) for r in stats} or {0: (0.0, 0.0)}), "routed")
    groups = max(1, -(-asked // query_group))
    sent = routed.withColumn("grp", F.pmod(F.xxhash64("vec_id"), F.lit(groups)).cast("int")).withColumn("cell", F.explode("cells")).drop("cells")
    sent = sent.withColumn("part", F.explode(F.sequence(F.lit(0), parts[F.col("cell")] - 1))).where("cell <> own_cell or part <> own_part")
    # Data go to the groups that ask for their part, and to no others.
    wanted = sent.select("cell", "part", "grp").distinct().toDF("w_cell", "w_part", "w_grp")
    copied = data.join(wanted, (data["cell"] == wanted["w_cell"]) & (data["part"] == wanted["w_part"])).select("cell", "part", F.col("w_grp").alias("grp"), "vec_id", "x")
    sent = sent.select("cell", "part", "grp", "vec_id", "x", "kth")
    far = copied.groupBy("cell", "part", "grp").cogroup(sent.groupBy("cell", "part", "grp")).applyInArrow(search, RESULT)
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), F.asc_nulls_last("vec_id"))
    return near.union(far).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
