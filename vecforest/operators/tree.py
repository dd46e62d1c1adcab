"""Quantile-code trees: bit-wise splits of code cells down to small leaves."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.staging import staged
from .encode import Edges

BITS = 8
LOCAL_ROWS = 200_000  # nodes of so many points are built inside one task
NODES = "space int, path string, parent string, depth int, bits array<int>, prefix array<int>, n_points long, is_leaf boolean, saturated boolean, split_dim int"


def shared_bits(lo: np.ndarray, hi: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Leading bits on which the least and greatest symbol agree, hence all between."""
    x = lo ^ hi
    return bits - np.where(x > 0, np.floor(np.log2(np.maximum(x, 1))).astype(int) + 1, 0)


def choose(n: int, used: np.ndarray, ones: np.ndarray, bits: int = BITS, rule: str = "even") -> int:
    """Dimension whose next bit splits n points most evenly; ties: fewer bits used, then the lower dimension. -1: none open.

    cycle takes the open dimension with the fewest bits, first the lowest; both
    skip one-sided dimensions while there are others.
    """
    open_ = np.flatnonzero(used < bits)
    if not len(open_):
        return -1
    sided = (ones[open_] == 0) | (ones[open_] == n)
    if rule == "even":
        key = np.lexsort((open_, used[open_], np.abs(2 * ones[open_] - n)))
    elif rule == "cycle":
        key = np.lexsort((open_, used[open_], sided))
    else:
        key = np.lexsort((open_, sided))
    return int(open_[key[0]])


def decide(n: int, used: np.ndarray, ones: np.ndarray, lo: np.ndarray, hi: np.ndarray, max_size: int, bits: int = BITS, rule: str = "even") -> tuple[str, int, np.ndarray]:
    """What becomes of a node: leaf, saturated, split (with its dimension) or tighten (with its new bits)."""
    if n <= max_size:
        return "leaf", -1, used
    dim = choose(n, used, ones, bits, rule)
    if dim < 0:
        return "saturated", -1, used
    if ones[dim] in (0, n):
        return "tighten", -1, np.maximum(used, shared_bits(lo, hi, bits))
    return "split", dim, used


def _record(space: int, path: str, used: np.ndarray, low: np.ndarray, n: int, what: str, dim: int, bits: int) -> tuple:
    parent = path.rpartition("|")[0] or None
    return (space, path, parent, path.count("|") + 1, used.tolist(), (low >> (bits - used)).tolist(), n, what != "split", what == "saturated", dim if what == "split" else None)


def grow(space: int, path: str, codes: np.ndarray, used: np.ndarray, max_size: int, bits: int = BITS, rule: str = "even", weights: np.ndarray | None = None) -> tuple[np.ndarray, list[tuple]]:
    """Builds the subtree of one node: leaf path of each point, and the node records. weights: how many points each code stands for."""
    leaf = np.empty(len(codes), dtype=object)
    nodes, todo = [], [(path, np.arange(len(codes)), used)]
    while todo:
        path, rows, used = todo.pop()
        c = codes[rows]
        n = len(rows) if weights is None else int(weights[rows].sum())
        while True:
            ones = (c >> np.maximum(bits - 1 - used, 0)) & 1
            ones = ones.sum(0) if weights is None else weights[rows] @ ones
            what, dim, used = decide(n, used, ones, c.min(0), c.max(0), max_size, bits, rule)
            if what != "tighten":
                break
        nodes.append(_record(space, path, used, c.min(0), n, what, dim, bits))
        if what != "split":
            leaf[rows] = path
            continue
        up = (c[:, dim] >> (bits - 1 - used[dim])) & 1
        below = used.copy()
        below[dim] += 1
        for bit in (0, 1):
            todo.append((f"{path}|{dim}:{bit}", rows[up == bit], below))
    return leaf, nodes


def _matrix(codes: pd.Series) -> np.ndarray:
    return np.stack([np.asarray(c, dtype=np.int64) for c in codes])


def build_forest(spaced: DataFrame, K: int, max_size: int = 64, strategy: str = "hybrid", bits: int = BITS, rule: str = "even", local_rows: int = LOCAL_ROWS) -> tuple[DataFrame, DataFrame]:
    """Node table, and the points with their leaf: (vec_id, space, code, proj, root_key, path, leaf_id).

    spaced: one row per point and space with root_key. levels splits all
    over-full nodes of all trees at once, one aggregation a level; subtrees
    builds each first-layer node inside one task; hybrid takes levels until
    nodes have local_rows points or fewer. All give the same trees.
    """
    points = staged(spaced.withColumn("path", F.col("root_key").cast("string")).withColumn("bits", F.array_repeat(F.lit(1), K)), "points")
    done_points, done_nodes = [], []
    limit = {"levels": max_size, "subtrees": 1 << 62, "hybrid": max(local_rows, max_size)}[strategy]
    current, columns = points, points.columns
    for _ in range(2 * bits * K + 2):
        ones = [F.sum(F.expr(f"shiftright(code[{j}], greatest({bits - 1} - bits[{j}], 0)) & 1")).alias(f"o{j}") for j in range(K)]
        lows = [F.min(F.get("code", F.lit(j))).alias(f"l{j}") for j in range(K)]
        highs = [F.max(F.get("code", F.lit(j))).alias(f"h{j}") for j in range(K)]
        sums = current.groupBy("space", "path").agg(F.count(F.lit(1)).alias("n"), F.first("bits").alias("bits"), *ones, *lows, *highs)
        arrays = sums.select("space", "path", "n", "bits", *[F.array(*[f"{x}{j}" for j in range(K)]).alias(x) for x in "olh"])

        def judge(batches, limit=limit):
            for batch in batches:
                out = []
                for r in batch.itertuples(index=False):
                    used = np.asarray(r.bits, dtype=np.int64)
                    if max_size < r.n <= limit:
                        out.append((r.space, r.path, "local", -1, used.tolist(), r.n, np.asarray(r.l).tolist()))
                        continue
                    what, dim, new = decide(int(r.n), used, np.asarray(r.o, dtype=np.int64), np.asarray(r.l, dtype=np.int64), np.asarray(r.h, dtype=np.int64), max_size, bits, rule)
                    out.append((r.space, r.path, what, dim, new.tolist(), r.n, np.asarray(r.l).tolist()))
                yield pd.DataFrame(out, columns=["space", "path", "what", "dim", "new", "n", "low"])

        judged = staged(arrays.mapInPandas(judge, "space int, path string, what string, dim int, new array<int>, n long, low array<int>"), "judged")

        def recorded(batches):
            for batch in batches:
                out = [_record(r.space, r.path, np.asarray(r.new, dtype=np.int64), np.asarray(r.low, dtype=np.int64), int(r.n), r.what, r.dim, bits) for r in batch.itertuples(index=False)]
                yield pd.DataFrame(out, columns=[c.split()[0] for c in NODES.split(", ")])

        done_nodes.append(judged.where(~F.col("what").isin("local", "tighten")).mapInPandas(recorded, NODES))
        with_what = current.join(judged.select("space", "path", "what", "dim", "new"), ["space", "path"])
        done_points.append(with_what.where(F.col("what").isin("leaf", "saturated")).select(*columns))
        local = with_what.where(F.col("what") == "local").select(*columns)
        if strategy != "levels":
            grown = staged(_grown(local, max_size, bits, rule), "grown")
            done_points.append(grown.where("n_points is null").select(*columns))
            done_nodes.append(grown.where("n_points is not null").select(*[c.split()[0] for c in NODES.split(", ")]))
        nxt = with_what.where(F.col("what").isin("split", "tighten"))
        split = F.col("what") == "split"
        bit = F.expr(f"shiftright(code[dim], {bits - 1} - bits[dim]) & 1")
        path = F.when(split, F.concat("path", F.lit("|"), F.col("dim").cast("string"), F.lit(":"), bit.cast("string"))).otherwise(F.col("path"))
        used = F.when(split, F.transform("bits", lambda b, i: F.when(i == F.col("dim"), b + 1).otherwise(b))).otherwise(F.col("new"))
        current = staged(nxt.withColumn("path2", path).withColumn("bits2", used).drop("path", "bits").withColumnsRenamed({"path2": "path", "bits2": "bits"}).select(*columns), "level")
        if current.isEmpty():
            break
    nodes, leaves = done_nodes[0], done_points[0]
    for x in done_nodes[1:]:
        nodes = nodes.unionByName(x)
    for x in done_points[1:]:
        leaves = leaves.unionByName(x)
    key = lambda c: F.xxhash64("space", c)
    nodes = nodes.withColumn("node_id", key("path")).withColumn("parent_id", F.when(F.col("parent").isNotNull(), key("parent")))
    return staged(nodes, "nodes"), leaves.withColumn("leaf_id", key("path")).drop("bits")


def _grown(local: DataFrame, max_size: int, bits: int, rule: str) -> DataFrame:
    """Point rows with their leaf path and node rows of the subtrees, told apart by n_points."""
    kinds = {f.name: f.dataType.simpleString() for f in local.schema}
    node_columns = [c for c in NODES.split(", ")]
    extra = [c for c in node_columns if c.split()[0] not in kinds]
    schema = ", ".join([*(f"{n} {t}" for n, t in kinds.items()), *extra])
    names = [*kinds, *(c.split()[0] for c in extra)]

    def one(key, pdf: pd.DataFrame) -> pd.DataFrame:
        used = np.asarray(pdf["bits"].iloc[0], dtype=np.int64)
        leaf, nodes = grow(int(key[0]), key[1], _matrix(pdf["code"]), used, max_size, bits, rule)
        rows = pdf.assign(path=leaf)
        made = pd.DataFrame(nodes, columns=[c.split()[0] for c in node_columns])
        return pd.concat([rows, made]).reindex(columns=names).astype(object).where(lambda d: d.map(lambda v: v is not None and not (isinstance(v, float) and v != v)), None)

    return local.groupBy("space", "path").applyInPandas(one, schema)


def build_incremental(spaced: DataFrame, K: int, max_size: int = 64, bits: int = BITS) -> DataFrame:
    """Points with the leaf that arrival order (vec_id) gives: a full leaf splits on the most even bit before it takes another point.

    One task holds one first-layer node, as a stream would.
    """

    def one(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("vec_id", kind="stable")
        codes = _matrix(pdf["code"])
        leaves: dict[str, list] = {str(key[1]): [np.ones(K, dtype=np.int64), []]}
        inner: dict[str, int] = {}
        for i, code in enumerate(codes):
            path = str(key[1])
            while True:
                while path in inner:
                    dim, used = inner[path]
                    path = f"{path}|{dim}:{(code[dim] >> (bits - 1 - used)) & 1}"
                used, rows = leaves[path]
                if len(rows) < max_size or (used >= bits).all():
                    rows.append(i)
                    break
                c = codes[rows]
                dim = choose(len(rows), used, ((c >> np.maximum(bits - 1 - used, 0)) & 1).sum(0), bits)
                up = (c[:, dim] >> (bits - 1 - used[dim])) & 1
                below = used.copy()
                below[dim] += 1
                for bit in (0, 1):
                    leaves[f"{path}|{dim}:{bit}"] = [below.copy(), [r for r, u in zip(rows, up, strict=True) if u == bit]]
                inner[path] = (dim, int(used[dim]))
                del leaves[path]
        leaf = np.empty(len(codes), dtype=object)
        for path, (_, rows) in leaves.items():
            leaf[rows] = path
        return pdf.assign(path=leaf)[["space", "vec_id", "path"]]

    return spaced.groupBy("space", "root_key").applyInPandas(one, "space int, vec_id long, path string")


def with_cells(nodes: DataFrame, edges: Edges, K: int, bits: int = BITS, unbounded: bool = False) -> DataFrame:
    """Adds lo and hi, the edges of each node's cell; unbounded opens the outer ones, for points that came after the build."""
    table = [np.array(e) for e in edges]

    def cells(space: pd.Series, used: pd.Series, prefix: pd.Series) -> pd.DataFrame:
        lo, hi = [], []
        for s, b, p in zip(space, used, prefix, strict=True):
            a, z = [], []
            for j in range(K):
                e, w = table[(s - 1) * K + j], bits - int(b[j])
                first, end = int(p[j]) << w, (int(p[j]) + 1) << w
                a.append(-np.inf if unbounded and first == 0 else float(e[first]))
                z.append(np.inf if unbounded and end == len(e) - 1 else float(e[end]))
            lo.append(a)
            hi.append(z)
        return pd.DataFrame({"lo": lo, "hi": hi})

    c = F.pandas_udf(cells, "lo array<double>, hi array<double>")("space", "bits", "prefix")
    return nodes.withColumn("cell", c).withColumn("lo", F.col("cell.lo")).withColumn("hi", F.col("cell.hi")).drop("cell")


def forest_stats(nodes: DataFrame) -> DataFrame:
    """By space: nodes, leaves, points, greatest depth and leaf, mean fill, saturated leaves."""
    leaf = F.col("is_leaf")
    return nodes.groupBy("space").agg(
        F.count(F.lit(1)).alias("nodes"), F.count_if(leaf).alias("leaves"), F.sum(F.when(leaf, F.col("n_points"))).alias("points"), F.max("depth").cast("long").alias("depth"),
        F.max(F.when(leaf, F.col("n_points"))).alias("largest"), F.avg(F.when(leaf, F.col("n_points"))).alias("fill"), F.count_if("saturated").alias("saturated"),
    )
