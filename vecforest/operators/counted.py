"""Forests and their tuned search without a stored entry for a point.

A tree depends on nothing but how many points have each code, so it is built
from these counts. A search walks each point down the trees again: its codes
are computed in the pass that needs them. Passes read the vectors where they
lie and send on counts, or k answers a query; no vector, projection or leaf of
a point is shuffled or staged. Nodes, and the order of the leaves for each
query, are held by the driver and go to all tasks.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.params import ForestParams
from ..plans.staging import staged
from .breakpoints import breakpoints, sampled, static_breakpoints
from .encode import Edges, edges_of
from .exact import Queries, collected, distances, ranked, smallest
from .projection import DECIMALS, dimension, project, projection_matrix
from .range_query import _bounds
from .tree import LOCAL_ROWS, NODES, _record, decide, forest_stats, grow, with_cells

ROWS_AT_ONCE = 500_000  # points whose codes a task counts together
BINS = 1024  # of the leaves in a query's order, to find the one that fills its budget


@dataclass
class CountedIndex:
    """L trees over the codes of points: node table with cells; which points a leaf has is computed when asked."""

    params: ForestParams
    matrix: np.ndarray
    edges: Edges
    nodes: DataFrame

    def stats(self) -> DataFrame:
        return forest_stats(self.nodes)


def cuts(points: DataFrame, params: ForestParams, method: str = "histogram_rounds") -> Edges:
    """The edges that build_index() takes, by the same sample; projections are made anew for each pass."""
    matrix = projection_matrix(dimension(points), params.K, params.L, params.seed)
    projected = project(points.select("vec_id", "embedding"), matrix).drop("embedding")
    part = sampled(projected, params.sample, regions=params.regions)
    return edges_of(breakpoints(projected, params.K, params.L, params.regions, method, part), params.K, params.L)


def static_cuts(edges: Edges, params: ForestParams) -> Edges:
    """Static inner edges between the outer ones of the data, as in build_index()."""
    inner = static_breakpoints(params.regions)
    return [[min(e[0], inner[0]), *inner, max(e[-1], inner[-1])] for e in edges]


def _vectors(batch: pa.RecordBatch) -> np.ndarray:
    return batch.column(batch.schema.get_field_index("embedding")).flatten().to_numpy(zero_copy_only=False).astype(np.float64, copy=False).reshape(batch.num_rows, -1)


def _codes(x: np.ndarray, matrix: np.ndarray, inner: list[np.ndarray]) -> np.ndarray:
    """Symbols (point, column), as encode() has them."""
    px = np.round(x @ matrix.T, DECIMALS)
    return np.stack([np.searchsorted(e, px[:, g], side="right") for g, e in enumerate(inner)], 1)


class Walk:
    """Nodes as arrays, and the way of codes (point, K) of a space down to the node where it ends."""

    def __init__(self, roots: np.ndarray, dim: np.ndarray, shift: np.ndarray, kids: np.ndarray, K: int, bits: int):
        self.roots, self.dim, self.shift, self.kids, self.K, self.bits = roots, dim, shift, kids, K, bits

    def ends(self, codes: np.ndarray, space: int | np.ndarray) -> np.ndarray:
        """Number of the node; space counts from 1."""
        at = self.roots[np.asarray(space) - 1, (codes >> (self.bits - 1)) @ (1 << np.arange(self.K - 1, -1, -1))]
        left = np.flatnonzero(self.dim[at] >= 0)
        while len(left):
            here = at[left]
            here = self.kids[here, (codes[left, self.dim[here]] >> self.shift[here]) & 1]
            at[left] = here
            left = left[self.dim[here] >= 0]
        return at


def _unpacked(code: np.ndarray, K: int, bits: int) -> np.ndarray:
    return np.stack([(code >> (bits * j)) & ((1 << bits) - 1) for j in range(K)], 1)


def code_counts(points: DataFrame, matrix: np.ndarray, edges: Edges, params: ForestParams) -> DataFrame:
    """(space, code, n): how many points have each code, its K symbols in one number."""
    K, L, bits = params.K, params.L, params.bits
    if K * bits > 63:
        raise ValueError(f"codes of {K * bits} bits; counted trees take 63")
    inner, weights = [np.array(e[1:-1]) for e in edges], 1 << (bits * np.arange(K))

    def flushed(held: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        every = np.concatenate(held)
        for s in range(L):
            code, n = np.unique(every[:, s], return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(code), s + 1, dtype=np.int32)), pa.array(code), pa.array(n.astype(np.int64))], ["space", "code", "n"])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, many = [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(_codes(_vectors(batch), matrix, inner).reshape(batch.num_rows, L, K) @ weights)
            many += batch.num_rows
            if many >= ROWS_AT_ONCE:
                yield from flushed(held)
                held, many = [], 0
        if held:
            yield from flushed(held)

    rows = points.select("embedding").mapInArrow(count, "space int, code long, n long")
    return staged(rows.groupBy("space", "code").agg(F.sum("n").alias("n")), "code-counts")


def build_counted(points: DataFrame, params: ForestParams, edges: Edges, rule: str = "even", local_rows: int = LOCAL_ROWS) -> CountedIndex:
    """The trees of build_index(), from counts of codes.

    Nodes of more than local_rows codes are split on the driver, a pass over the
    counts for each level; the tasks finish the others.
    """
    K, L, bits, most = params.K, params.L, params.bits, params.max_size
    matrix = projection_matrix(dimension(points), K, L, params.seed)
    counts = code_counts(points, matrix, edges, params)
    spark = points.sparkSession
    roots = np.arange(L << K).reshape(L, 1 << K)
    names = [(s + 1, str(r)) for s in range(L) for r in range(1 << K)]
    used = [np.ones(K, dtype=np.int64) for _ in names]
    dim, shift, kids = [-1] * len(names), [0] * len(names), [(0, 0)] * len(names)
    open_, local, done = set(range(len(names))), [], []
    while open_:
        walk = Walk(roots, np.array(dim), np.array(shift), np.array(kids), K, bits)
        taken, asked = np.array(used), np.isin(np.arange(len(names)), list(open_))

        def seen(batches: Iterator[pa.RecordBatch], walk=walk, taken=taken, asked=asked) -> Iterator[pa.RecordBatch]:
            m = len(asked)
            n, rows, ones = np.zeros(m), np.zeros(m), np.zeros((m, K))
            lo, hi = np.full((m, K), 1 << bits), np.full((m, K), -1)
            for batch in batches:
                space, code, many = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
                c = _unpacked(code, K, bits)
                at = walk.ends(c, space)
                ok = asked[at]
                c, at, many = c[ok], at[ok], many[ok]
                n += np.bincount(at, many, m)
                rows += np.bincount(at, minlength=m)
                for j in range(K):
                    ones[:, j] += np.bincount(at, many * ((c[:, j] >> np.maximum(bits - 1 - taken[at, j], 0)) & 1), m)
                np.minimum.at(lo, at, c)
                np.maximum.at(hi, at, c)
            some = np.flatnonzero(rows)
            sums = np.concatenate([n[:, None], rows[:, None], ones], 1).astype(np.int64)[some]
            yield pa.RecordBatch.from_arrays([pa.array(some.astype(np.int32)), pa.array(list(sums)), pa.array(list(lo[some])), pa.array(list(hi[some]))] if len(some) else [pa.array([], t) for t in (pa.int32(), *[pa.list_(pa.int64())] * 3)], ["node", "sums", "lo", "hi"])

        parts = counts.select("space", "code", "n").mapInArrow(seen, "node int, sums array<long>, lo array<long>, hi array<long>")
        each = lambda f, c, w: F.array(*[f(F.get(c, F.lit(j))) for j in range(w)]).alias(c)
        found = parts.groupBy("node").agg(each(F.sum, "sums", K + 2), each(F.min, "lo", K), each(F.max, "hi", K)).collect()
        open_ = set()
        for r in found:
            at, (n, rows, *ones) = r["node"], r["sums"]
            if n > most and rows <= local_rows:
                local.append(at)
                continue
            low = np.array(r["lo"])
            what, d, new = decide(n, used[at], np.array(ones), low, np.array(r["hi"]), most, bits, rule)
            used[at] = new
            if what == "tighten":
                open_.add(at)
                continue
            done.append(_record(*names[at], new, low, n, what, d, bits))
            if what != "split":
                continue
            dim[at], shift[at], kids[at] = d, bits - 1 - int(new[d]), (len(names), len(names) + 1)
            below = new.copy()
            below[d] += 1
            for bit in (0, 1):
                open_.add(len(names))
                names.append((names[at][0], f"{names[at][1]}|{d}:{bit}"))
                used.append(below.copy())
                dim.append(-1)
                shift.append(0)
                kids.append((0, 0))
    nodes = spark.createDataFrame([tuple(v.item() if isinstance(v, np.generic) else v for v in r) for r in done], NODES)
    if local:
        walk, wanted = Walk(roots, np.array(dim), np.array(shift), np.array(kids), K, bits), np.isin(np.arange(len(names)), local)
        start = {at: (*names[at], used[at]) for at in local}

        def dealt(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                space, code, many = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
                at = walk.ends(_unpacked(code, K, bits), space)
                ok = wanted[at]
                yield pa.RecordBatch.from_arrays([pa.array(at[ok].astype(np.int32)), pa.array(code[ok]), pa.array(many[ok])], ["node", "code", "n"])

        def one(pdf: pd.DataFrame) -> pd.DataFrame:
            space, path, bits_used = start[int(pdf["node"].iloc[0])]
            made = grow(space, path, _unpacked(pdf["code"].to_numpy(), K, bits), bits_used, most, bits, rule, pdf["n"].to_numpy())[1]
            out = pd.DataFrame(made, columns=[c.split()[0] for c in NODES.split(", ")])
            return out.assign(split_dim=out["split_dim"].astype("Int32"))

        nodes = nodes.unionByName(counts.select("space", "code", "n").mapInArrow(dealt, "node int, code long, n long").groupBy("node").applyInPandas(one, NODES))
    key = lambda c: F.xxhash64("space", c)
    nodes = nodes.withColumn("node_id", key("path")).withColumn("parent_id", F.when(F.col("parent").isNotNull(), key("parent")))
    return CountedIndex(params, matrix, edges, staged(with_cells(nodes, edges, K, bits), "cells"))


def _columns(df: DataFrame) -> dict[str, np.ndarray]:
    """Columns on the driver; arrays of equal length as one matrix."""
    t = df.toArrow().combine_chunks()
    out = {}
    for name in t.column_names:
        c = t.column(name)
        flat = np.concatenate([x.flatten().to_numpy(zero_copy_only=False) if pa.types.is_list(c.type) else x.to_numpy(zero_copy_only=False) for x in c.chunks] or [np.zeros(0)])
        out[name] = flat.reshape(len(t), -1) if pa.types.is_list(c.type) else flat
    return out


def _walked(index: CountedIndex, q: Queries) -> tuple[Walk, np.ndarray]:
    """The trees as arrays whose last nodes are numbers of leaves, and the place of each leaf in each query's order (leaf, query)."""
    K, L, bits = index.params.K, index.params.L, index.params.bits
    root = F.col("parent_id").isNull()
    last = F.when(root, F.col("path").cast("int")).otherwise(F.substring("path", -1, 1).cast("int"))
    t = _columns(index.nodes.select("space", "node_id", F.coalesce("parent_id", F.lit(0)).alias("parent_id"), root.alias("root"), last.alias("last"), "is_leaf", F.coalesce("split_dim", F.lit(-1)).alias("dim"), F.when(~F.col("is_leaf"), bits - 1 - F.get("bits", F.col("split_dim"))).otherwise(0).alias("shift")))
    by = np.lexsort((t["node_id"], t["space"], ~t["is_leaf"]))  # leaves first, by space and id
    t = {k: v[by] for k, v in t.items()}
    roots, kids = np.full((L, 1 << K), -1, dtype=np.int64), np.full((len(by), 2), -1, dtype=np.int32)
    roots[t["space"][t["root"]] - 1, t["last"][t["root"]]] = np.flatnonzero(t["root"])
    for s in range(1, L + 1):
        inner, below = np.flatnonzero((t["space"] == s) & ~t["is_leaf"]), np.flatnonzero((t["space"] == s) & ~t["root"])
        if len(below):
            kids[inner[np.searchsorted(t["node_id"][inner], t["parent_id"][below])], t["last"][below]] = below
    walk = Walk(roots, t["dim"].astype(np.int8), t["shift"].astype(np.int8), kids, K, bits)
    leaves = _columns(index.nodes.where("is_leaf").select("space", "node_id", "lo", "hi"))
    by = np.lexsort((leaves["node_id"], leaves["space"]))
    leaves = {k: v[by] for k, v in leaves.items()}
    pq = np.round(q.vectors @ index.matrix.T, DECIMALS).reshape(len(q), L, K)
    place = np.empty((len(by), len(q)), dtype=np.int32)
    for a in range(len(q)):
        lb = np.concatenate([_bounds(leaves["lo"][at], leaves["hi"][at], pq[a, s - 1])[0] for s in range(1, L + 1) if len(at := np.flatnonzero(leaves["space"] == s))])
        place[np.argsort(lb, kind="stable"), a] = np.arange(len(by))
    return walk, place


def ck_ann_counted(index: CountedIndex, points: DataFrame, queries: DataFrame | Queries, k: int) -> DataFrame:
    """ck_ann_tuned(), whose leaves are computed: (query_id, rank, vec_id, dist, pooled).

    Two passes count the points by the first leaf that brings them in, in parts
    of a query's leaves and then leaf by leaf in the part that fills its budget;
    a third takes the nearest of the pool. Each row is a point of its own; the
    queries' ids have to differ.
    """
    p = index.params
    q = queries if isinstance(queries, Queries) else collected(queries)
    if len(np.unique(q.ids)) < len(q):
        raise ValueError("ids of queries repeat")
    spark, Q, K, L = points.sparkSession, len(q), p.K, p.L
    own = {r[0] for r in points.where(F.col("vec_id").isin([int(i) for i in q.ids])).select("vec_id").collect()}
    n = points.count()
    others = np.array([n - (int(i) in own) for i in q.ids])
    need = np.array([min(p.need(int(m), k), max(int(m), 1)) for m in others])
    walk, place = _walked(index, q)
    none = np.iinfo(np.int32).max
    width = max(1, -(-len(place) // BINS))  # leaves a part
    sent = spark.sparkContext.broadcast((walk, place))
    matrix, inner = index.matrix, [np.array(e[1:-1]) for e in index.edges]
    rows = points.select("vec_id", "embedding")

    def entries(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids, vectors, and the place of the first leaf that brings in each point (point, query)."""
        walk, place = sent.value
        x, ids = _vectors(batch), batch.column(batch.schema.get_field_index("vec_id")).to_numpy()
        codes = _codes(x, matrix, inner).reshape(len(x), L, K)
        at = place[walk.ends(codes[:, 0], 1)]
        for s in range(1, L):
            np.minimum(at, place[walk.ends(codes[:, s], s + 1)], out=at)
        mine = np.minimum(np.searchsorted(q.ids, ids), Q - 1)
        same = np.flatnonzero(q.ids[mine] == ids)
        at[same, mine[same]] = none
        return ids, x, at

    def counted(first: np.ndarray, each: int, many: int) -> np.ndarray:
        """By query: points in each of `many` parts of `each` leaves from the first on."""

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums = np.zeros(Q * many, dtype=np.int64)
            for batch in batches:
                if not batch.num_rows:
                    continue
                at = entries(batch)[2]
                part = (at.astype(np.int64) - first) // each
                ok = (at != none) & (part >= 0) & (part < many)
                sums += np.bincount((part + many * np.arange(Q))[ok], minlength=Q * many)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(Q, dtype=np.int32)), pa.array([x.tobytes() for x in sums.reshape(Q, many)], pa.binary())], ["a", "sums"])

        def added(pdf: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"a": pdf["a"].iloc[:1], "sums": [np.sum([np.frombuffer(x, dtype=np.int64) for x in pdf["sums"]], axis=0).tobytes()]})

        total = np.zeros((Q, many), dtype=np.int64)
        for r in rows.mapInArrow(count, "a int, sums binary").groupBy("a").applyInPandas(added, "a int, sums binary").collect():
            total[r["a"]] = np.frombuffer(bytes(r["sums"]), dtype=np.int64)
        return total

    upto = np.cumsum(counted(np.zeros(Q, dtype=np.int64), width, BINS), 1)
    part = (upto < need[:, None]).sum(1).clip(max=BINS - 1)
    before = np.where(part > 0, upto[np.arange(Q), np.maximum(part - 1, 0)], 0)
    upto = before[:, None] + np.cumsum(counted(part * width, 1, width), 1)
    at = (upto < need[:, None]).sum(1).clip(max=width - 1)
    stop, pooled = part * width + at, upto[np.arange(Q), at]

    def nearest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = [(np.zeros(0, dtype=np.int64), np.zeros(0)) for _ in range(Q)]
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, x, at = entries(batch)
            for a in range(Q):
                some = np.flatnonzero(at[:, a] <= stop[a])
                if len(some):
                    i, d = np.r_[best[a][0], ids[some]], np.r_[best[a][1], distances(x[some], q.vectors[a])]
                    first = smallest(d, i, k)
                    best[a] = i[first], d[first]
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(q.ids, [len(i) for i, _ in best])), pa.array(np.concatenate([i for i, _ in best])), pa.array(np.concatenate([d for _, d in best]))], ["query_id", "vec_id", "dist"])

    sizes = spark.createDataFrame([(int(i), int(m)) for i, m in zip(q.ids, pooled, strict=True)], "query_id long, pooled long")
    return ranked(rows.mapInArrow(nearest, "query_id long, vec_id long, dist double"), k).join(F.broadcast(sizes), "query_id")
