"""The experiments, W0 to W22, as tidy rows (workload, method, params, measure, value).

Deterministic parts have queries with SQL; what is timed here is not compared.
Parallelism is varied by the number of partitions, since a session keeps its
slots.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .baselines import projected as rivals
from .baselines.layered_graph import layered_graph_ann
from .baselines.multi_codebook import multi_codebook_ann
from .functions.params import SUCCESS, ForestParams, beta_table
from .operators import ann, engine, metrics, views
from .operators.breakpoints import breakpoints, sampled, selected, static_breakpoints
from .operators.encode import by_space, edges_of, encode, region_balance, with_root_key
from .operators.exact import Queries, collected, exact_knn
from .operators.projection import dimension, project, projection_matrix
from .operators.range_query import build_index, range_query
from .operators.tree import build_forest
from .plans.staging import removed, shared_dir, staged

Rows = list[tuple[str, str, str, str, float]]


def _time(run: Callable[[], object]) -> float:
    start = time.perf_counter()
    run()
    return time.perf_counter() - start


def _accuracy(result: DataFrame, truth: DataFrame, k: int) -> tuple[float, float]:
    r = metrics.recall(result, truth, k).agg(F.avg("recall")).first()[0]
    o = metrics.overall_ratio(result, truth).agg(F.avg("ratio")).first()[0]
    return float(r or 0.0), float(o or 0.0)


def _setup(points: DataFrame, n_q: int = 20) -> tuple[DataFrame, Queries]:
    rest, asked = views.held_out(points, n_q)
    return staged(rest.select("vec_id", "embedding"), "points"), collected(asked)


def methods(k: int) -> dict[str, Callable[[DataFrame, Queries], DataFrame]]:
    return {
        "forest": lambda v, q: ann.ck_ann(v, q, k).result,
        "query_box": lambda v, q: rivals.query_box_ann(v, q, k).result,
        "circular_run": lambda v, q: rivals.circular_run_ann(v, q, k),
        "pivot_metric": lambda v, q: rivals.pivot_metric_ann(v, q, k).result,
        "static_bucket": lambda v, q: rivals.static_bucket_ann(v, q, k),
        "collision_count": lambda v, q: rivals.collision_count_ann(v, q, k).result,
        "metric_order": lambda v, q: rivals.metric_order_ann(v, q, k).result,
        "layered_graph": lambda v, q: layered_graph_ann(v, q, k),
        "multi_codebook": lambda v, q: multi_codebook_ann(v, q, k, exact=4 * k),
    }


def w0_holdout(points: DataFrame, n_q: int = 100) -> Rows:
    rest, asked = views.held_out(points, n_q)
    return [("W0", "split", f"n_q={n_q}", m, float(df.count())) for m, df in (("points", rest), ("queries", asked))]


def w1_breakdown(points: DataFrame, params: ForestParams = ForestParams(K=4)) -> Rows:
    matrix = projection_matrix(dimension(points), params.K, params.L, params.seed)
    pr = staged(project(points.select("vec_id", "embedding"), matrix).drop("embedding"), "projected")
    out: Rows = []
    for m in ("full_sort", "select_rounds", "histogram_rounds", "approx_percentile", "kll"):
        out.append(("W1", m, f"regions={params.regions}", "seconds", _time(lambda m=m: breakpoints(pr, params.K, params.L, params.regions, m))))
    counts = selected(pr, params.K, params.regions).agg(F.sum("comparisons"), F.sum("sort_comparisons")).first()
    out += [("W1", "selection", "", "comparisons", float(counts[0])), ("W1", "sort", "", "comparisons", float(counts[1]))]
    edges = edges_of(breakpoints(pr, params.K, params.L, params.regions), params.K, params.L)
    spaced = with_root_key(by_space(encode(pr, edges), params.K, params.L), params.K)
    out.append(("W1", "encode", "", "seconds", metrics.timed(spaced)))
    out.append(("W1", "tree", "", "seconds", _time(lambda: metrics.timed(build_forest(spaced, params.K, params.max_size)[1]))))
    return out


def w2_tuned(points: DataFrame, k: int = 10, sizes: tuple[int, ...] = (16, 64, 256)) -> Rows:
    v, q = _setup(points)
    truth, out = exact_knn(v, q, k), []
    for size in sizes:
        index = build_index(v, ForestParams(K=4, max_size=size))
        first = engine.first_radius(v, q, ann.spaces_of(v, index.params), {int(i): index.params.need(v.count(), k) for i in q.ids})
        r = {i: x / index.params.eps for i, x in first.items()}
        for form, run in (("strict", lambda: ann.ck_ann_rounds(index, v, q, k, r)), ("tuned", lambda: ann.ck_ann_tuned(index, v, q, k))):
            res = None

            def go(run=run):
                nonlocal res
                res = staged(run(), "result")

            seconds = _time(go)
            recall, ratio = _accuracy(res, truth, k)
            out += [("W2", form, f"max_size={size}", m, x) for m, x in (("seconds", seconds), ("recall", recall), ("ratio", ratio))]
    return out


def w3_w6_parallel(points: DataFrame, parts: tuple[int, ...] = (1, 2, 4, 8), k: int = 10) -> Rows:
    out, base = [], {}
    for p in parts:
        v = staged(points.select("vec_id", "embedding").repartition(p, "vec_id"), "points").coalesce(p)
        q = collected(views.queries_of(points))
        index = _time(lambda v=v: build_index(v, ForestParams(K=4)))
        ask = _time(lambda v=v: ann.ck_ann(v, q, k).result.collect())
        base = base or {"index": index, "query": ask}
        out += [("W3", "forest", f"partitions={p}", "index_seconds", index), ("W4", "forest", f"partitions={p}", "query_seconds", ask)]
        out += [("W6", "forest", f"partitions={p}", "index_speedup", metrics.speedup(base["index"], index)), ("W6", "forest", f"partitions={p}", "query_speedup", metrics.speedup(base["query"], ask))]
    return out


def w5_queues(points: DataFrame, grid: tuple[tuple[int, int], ...] = ((1, 1), (4, 1), (4, 2), (4, 4), (8, 4))) -> Rows:
    v, q = _setup(points)
    index, out, first = build_index(v, ForestParams(K=4, max_size=16)), [], None
    for workers, queues in grid:
        rows: set = set()
        seconds = _time(lambda w=workers, n=queues: rows.update(tuple(r) for r in range_query(index, q, 3.0, n_workers=w, n_queues=n).select("query_id", "space", "vec_id").collect()))
        first = first or rows
        out += [("W5", "forest", f"workers={workers},queues={queues}", "seconds", seconds), ("W5", "forest", f"workers={workers},queues={queues}", "equal", float(rows == first))]
    return out


def w7_w8_vary(points: DataFrame, k: int = 10) -> Rows:
    v, q = _setup(points)
    truth, out = exact_knn(v, q, k), []
    for tag, grid in (("W7", [ForestParams(L=x) for x in (1, 2, 4, 8)]), ("W8", [ForestParams(K=x) for x in (4, 8, 12, 16)] + [ForestParams(K=4, L=16)])):
        for p in grid:
            recall, ratio = _accuracy(ann.ck_ann(v, q, k, p).result, truth, k)
            out += [(tag, "forest", f"K={p.K},L={p.L}", m, x) for m, x in (("recall", recall), ("ratio", ratio), ("bytes", float(sum(metrics.index_size(v.count(), p).values()))))]
    return out


def w9_memory(spark: SparkSession, sf_dir: str) -> Rows:
    out: Rows = []
    for name, view in views.VIEWS.items():
        v = view(spark, sf_dir)
        n, d = v.count(), dimension(v)
        out.append(("W9", name, f"n={n},d={d}", "bytes", float(sum(metrics.memory(n, d, ForestParams()).values()))))
    return out


def _bytes_under(spark: SparkSession, path: str) -> int:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(p).getLength()


def w9b_scales(spark: SparkSession, sf_dir: str, copies: tuple[int, ...] = (1, 4), params: ForestParams = ForestParams(K=4)) -> Rows:
    """Bytes of the files of a saved index over copies of one set, and the bytes of a query's memory by their numbers."""
    out: Rows = []
    for m in copies:
        v = staged(views.emb64_scaled(spark, sf_dir, m).select("vec_id", "embedding"), "points")
        index, path = build_index(v, params), f"{shared_dir(spark)}/index-{uuid.uuid4().hex}"
        index.save(path)
        n, nodes = v.count(), index.nodes.count()
        out += [("W9b", "forest", f"copies={m}", x, float(y)) for x, y in (("n", n), ("file_bytes", _bytes_under(spark, path)), ("memory_bytes", sum(metrics.memory(n, dimension(v), params, nodes, params.need(n, 50)).values())))]
        removed(spark, path)
    return out


def w11_builds(points: DataFrame, k: int = 10) -> Rows:
    """Seconds to build each index: our trees, box tiles, graph and codebooks (the last two with one query, as they build when asked)."""
    v, q = _setup(points, 1)
    pr = staged(project(v, projection_matrix(dimension(v), 4, 4)), "projected")
    builds = {"forest": lambda: build_index(v, ForestParams(K=4)), "box_tiles": lambda: metrics.timed(rivals.box_tiles(pr)), "layered_graph": lambda: layered_graph_ann(v, q, k).collect(), "multi_codebook": lambda: multi_codebook_ann(v, q, k, exact=4 * k).collect()}
    return [("W11", name, "", "index_seconds", _time(run)) for name, run in builds.items()]


def w12_w13_curves(points: DataFrame, k: int = 10, betas: tuple[float, ...] = (0.01, 0.05, 0.2)) -> Rows:
    """Recall and ratio against seconds, over the budget of the forest and of the rivals that pool by budget; seconds by step for the forest over its index."""
    v, q = _setup(points)
    truth, out = staged(exact_knn(v, q, k), "truth"), []
    index = build_index(v, ForestParams(K=4))
    for beta in betas:
        for name, run in (("forest", lambda b=beta: ann.ck_ann(v, q, k, ForestParams(beta=b)).result), ("forest_index", lambda b=beta: ann.ck_ann_index(replace(index, params=index.params.with_(beta=b)), v, q, k)), ("query_box", lambda b=beta: rivals.query_box_ann(v, q, k, beta=b).result)):
            res: list[DataFrame] = []
            seconds = _time(lambda run=run, res=res: res.append(staged(run(), "result")))
            recall, ratio = _accuracy(res[0], truth, k)
            out += [("W12", name, f"beta={beta}", "seconds", seconds), ("W12", name, f"beta={beta}", "recall", recall), ("W13", name, f"beta={beta}", "ratio", ratio)]
    reach = index.params.eps * 1.1
    pool = range_query(index, q, reach).select("query_id", "vec_id").distinct()
    steps = metrics.stage_times({"range": lambda: range_query(index, q, reach), "select": lambda: pool, "rerank": lambda: ann.rerank(pool, v, q, k)})
    return out + [("W4", "forest_index", f"step={x}", "seconds", s / len(q)) for x, s in steps.items()]


def w10_to_w13_rivals(points: DataFrame, k: int = 10, names: tuple[str, ...] | None = None) -> Rows:
    """Time, recall and ratio of each method; the recall-time and ratio-time points at its default settings."""
    v, q = _setup(points)
    truth, out = exact_knn(v, q, k), []
    for name, run in methods(k).items():
        if names and name not in names:
            continue
        res = None

        def go(run=run):
            nonlocal res
            res = staged(run(v, q), "result")

        seconds = _time(go)
        recall, ratio = _accuracy(res, truth, k)
        out += [("W12", name, "", m, x) for m, x in (("seconds", seconds), ("recall", recall), ("ratio", ratio))]
    return out


def w14_size(spark: SparkSession, sf_dir: str, copies: tuple[int, ...] = (1, 4), k: int = 10) -> Rows:
    out: Rows = []
    for m in copies:
        v, q = _setup(views.emb64_scaled(spark, sf_dir, m))
        truth = exact_knn(v, q, k)
        recall, ratio = _accuracy(ann.ck_ann(v, q, k).result, truth, k)
        out += [("W14", "forest", f"copies={m}", x, y) for x, y in (("n", float(v.count())), ("recall", recall), ("ratio", ratio))]
    return out


def w15_k(points: DataFrame, ks: tuple[int, ...] = (1, 10, 20, 50), n_q: int = 20) -> Rows:
    v, q = _setup(points, n_q)
    out: Rows = []
    for k in ks:
        recall, ratio = _accuracy(ann.ck_ann(v, q, k).result, exact_knn(v, q, k), k)
        out += [("W15", "forest", f"k={k}", "recall", recall), ("W15", "forest", f"k={k}", "ratio", ratio)]
    return out


def w16_cumulative(points: DataFrame, k: int = 10) -> Rows:
    """Queries that the forest answers before the rival has built its index."""
    v, q = _setup(points)
    index = _time(lambda: build_index(v, ForestParams(K=4)))
    ask = _time(lambda: ann.ck_ann(v, q, k).result.collect()) / max(len(q), 1)
    out: Rows = []
    for name, run in (("layered_graph", layered_graph_ann), ("multi_codebook", multi_codebook_ann)):
        rival = _time(lambda run=run: run(v, q, k).collect())
        out.append(("W16", name, f"k={k}", "break_even_queries", float(metrics.break_even((index, ask), (rival, 0.0)))))
    return out


def w18_beta() -> Rows:
    return [("W18", "theory", f"L={L}", m, x) for L, e, b in beta_table() for m, x in (("eps", e), ("beta", b))]


def w19_parallel_equal(points: DataFrame, k: int = 10) -> Rows:
    v, q = _setup(points)
    a = {tuple(r) for r in ann.ck_ann(v.coalesce(1), q, k).result.collect()}
    out: Rows = []
    for p in (2, 8):
        b = {tuple(r) for r in ann.ck_ann(v.repartition(p), q, k).result.collect()}
        out.append(("W19", "forest", f"partitions={p}", "equal", float(a == b)))
    return out


def w20_guarantee(points: DataFrame, c: float = 1.2, seeds: int = 8, k: int = 10) -> Rows:
    """Rates of the near and the far event, and of valid answers by rank, over seeds, at the theoretical beta and a safe first radius."""
    v, q = _setup(points, 10)
    truth = staged(exact_knn(v, q, k), "truth")
    near = {r["query_id"]: r["dist"] for r in truth.where("rank = 1").collect()}
    rates = [0.0, 0.0, 0.0]
    for s in range(seeds):
        p = ForestParams(c=c, seed=s + 1)
        p = p.with_(beta=p.beta_theory)
        res = ann.ck_ann(v, q, k, p, r_min={i: max(0.99 * d, 1e-6) for i, d in near.items()}).result
        both = truth.select("query_id", "rank", F.col("dist").alias("exact")).join(res.select("query_id", "rank", "dist"), ["query_id", "rank"], "left")
        rates[0] += both.agg(F.avg(F.coalesce((F.col("dist") <= F.col("exact") * c * c + 1e-9).cast("double"), F.lit(0.0)))).first()[0]
        e = ann.event_rates(v, q, sum(near.values()) / len(near), p).agg(F.avg(F.col("event1").cast("double")), F.avg(F.col("event3").cast("double"))).first()
        rates[1] += e[0]
        rates[2] += e[1]
    names = (("valid_by_rank", SUCCESS), ("event1", 1 - 1 / 2.718281828), ("event3", 0.5))
    return [("W20", "forest", f"c={c}", m, x / seeds) for (m, _), x in zip(names, rates, strict=True)] + [("W20", "bound", f"c={c}", m, b) for m, b in names]


def w21_static(points: DataFrame) -> Rows:
    matrix = projection_matrix(dimension(points), 4, 4)
    pr = staged(project(points.select("vec_id", "embedding"), matrix).drop("embedding"), "projected")
    inner = static_breakpoints(256)
    codes = {"dynamic": encode(pr, edges_of(breakpoints(pr, 4, 4), 4, 4)), "static": encode(pr, [[float("-inf"), *inner, float("inf")]] * 16)}
    return [("W21", m, "", "most_in_a_region", float(region_balance(df, 4).agg(F.avg("most")).first()[0])) for m, df in codes.items()]


def w22_tiles(points: DataFrame) -> Rows:
    v = staged(points.select("vec_id", "embedding"), "points")
    pr = staged(project(v, projection_matrix(dimension(v), 4, 4)), "projected")
    return [("W22", "box_tiles", "", "seconds", metrics.timed(rivals.box_tiles(pr))), ("W22", "code_tree", "", "seconds", _time(lambda: build_index(v, ForestParams(K=4), method="approx_percentile")))]


def sampled_share(points: DataFrame, share: float) -> DataFrame:
    """The breakpoint sample of a view, as W1 and the index take it."""
    return sampled(points, share)
