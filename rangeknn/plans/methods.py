"""Several attributes, all-range graphs, join forms and the experiments that compare the methods."""

from __future__ import annotations

import posixpath
import time
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rangeknn.operators import baselines, exact, frontier, index, kernels, metrics, multi, multi_range
from rangeknn.operators.index import graph_kernel, materialise
from rangeknn.plans.surface import registered
from rangeknn.plans.workload import E_SQL, LARGE_EF, SMALL, Setup, index_sql, intervals_sql, measured, scan_graph_sql, shown
from rangeknn.sources.catalog import held_out, intervals, micros, objects, table
from rangeknn.streaming import stream, table_function

#: Two attributes: price and order date; the date interval is the same for all queries.
_DAYS = ("1996-01-01", "1999-01-01")
_E2 = f"""WITH o AS (SELECT vec_id AS id, embedding::DOUBLE[] AS vec, o_totalprice::DOUBLE AS attr, o_orderdate AS day FROM embeddings JOIN orders ON vec_id = o_orderkey),
r AS (SELECT *, row_number() OVER (ORDER BY attr, id) AS rank FROM o WHERE id % 25 <> 7), {intervals_sql("0.5")},
d AS (SELECT qid, id, list_distance(vec, qvec) AS dist FROM q JOIN r ON attr BETWEEN lo AND hi AND day BETWEEN TIMESTAMP '{_DAYS[0]}' AND TIMESTAMP '{_DAYS[1]}')
SELECT qid, rn, id, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rn FROM d) WHERE rn <= 10"""


class Boxes:
    """Held-out queries with a price interval of half of the objects and three years of dates."""

    def __init__(self, spark: SparkSession, sf_dir: str, share: float = 0.5, k: int = 10) -> None:
        days = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("id"), micros("o_orderdate").cast("double").alias("day"))
        objs, asked = held_out(objects(spark, sf_dir).join(days, "id").where("day is not null").withColumn("attrs", F.array("attr", "day")).drop("attr", "day"))
        self.ranked = materialise(multi.rank_first(objs), "box_ranked")
        day = F.struct(*(F.unix_micros(F.lit(d).cast("timestamp")).cast("double").alias(n) for d, n in zip(_DAYS, ("lo", "hi"), strict=True)))
        price = F.struct("lo", "hi")
        self.queries = materialise(intervals(self.ranked, asked, share, k).select("qid", "qvec", F.array(price, day).alias("box"), "k"), "box_queries")

    def built(self) -> DataFrame:
        return multi.build(self.ranked, SMALL)


def _boxed(kernel: Callable, exact_form: bool = True) -> Callable[[SparkSession, str], DataFrame]:
    """The rows found, or, of an approximate kernel, what they are worth."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        b = Boxes(spark, sf_dir)
        built = b.built()
        found = multi.box_search(built, b.queries, kernel())
        return shown(found) if exact_form else measured(found, multi.box_search(built, b.queries, multi.box_scan))

    return run


def _named(name: str, sql: str | None, run: Callable[[SparkSession, str], DataFrame]) -> None:
    run.__name__ = name
    registered(sql)(run)


_named("box_search_saturated", _E2, _boxed(lambda: multi.box_kernel(LARGE_EF)))
_named("box_prefilter_scan", _E2, _boxed(lambda: multi.box_scan))
_named("box_search_approx", None, _boxed(lambda: multi.box_kernel(64), False))
_named("box_compressed_approx", None, _boxed(lambda: multi_range.per_shard(multi_range.CompressedRanges), False))
_named("box_segment_tree_approx", None, _boxed(lambda: multi_range.per_shard(baselines.SegmentTree), False))


def _all_range(method: Callable[..., DataFrame], **how) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s = Setup(spark, sf_dir)
        return measured(method(s.packed(), s.queries, **how), s.truth())

    return run


_named("thinned_ranges_approx", None, _all_range(multi_range.stored_ranges_search))
_named("range_covers_approx", None, _all_range(multi_range.stored_ranges_search, choose="covers"))
_named("segment_bitmap_approx", None, _all_range(multi_range.segment_bitmap_search))
_named("compressed_max_leap_approx", None, _all_range(multi_range.compressed_search))
_named("compressed_min_leap_approx", None, _all_range(multi_range.compressed_search, leap="min"))
_named("rectangle_labels_approx", None, _all_range(multi_range.rectangle_search))


_KNN = f"""WITH {E_SQL}, {intervals_sql()}, d AS (SELECT qid, id, list_distance(vec, qvec) AS dist FROM q JOIN r ON attr BETWEEN lo AND hi)
SELECT qid, rn, id, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rn FROM d) WHERE rn <= 10"""


@registered(_KNN)
def range_search_frontier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The index searched in hops of joins, with a pool that holds the whole interval."""
    s = Setup(spark, sf_dir)
    links = index.edges(s.built()).select(F.col("src_rank").alias("src"), F.col("dst_rank").alias("dst"))
    return shown(frontier.frontier_search(s.ranked, links, index.to_ranks(s.queries, s.ranked), LARGE_EF, shard_rows=index.SHARD_ROWS))


@registered(_KNN)
def udtf_range_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The saved index asked from SQL, one call a query."""
    s = Setup(spark, sf_dir)
    built = s.built()
    path = built.inputFiles()[0].rsplit("/", 1)[0]
    table_function.register(spark, ef=LARGE_EF)
    s.queries.createOrReplaceTempView("rk_queries")
    return spark.sql(f"SELECT qid, t.rn, t.id, round(sqrt(t.d2), 6) AS dist FROM rk_queries, LATERAL range_knn('{path}', qvec, lo, hi, k) t")


def _by_rank(ranked: DataFrame, pairs: DataFrame) -> DataFrame:
    """Pairs (src, dst) of ids as pairs of ranks."""
    place = ranked.select("id", "rank")
    return pairs.join(place.toDF("src", "a"), "src").join(place.toDF("dst", "b"), "dst").select(F.col("a").alias("src"), F.col("b").alias("dst"))


def _lune_sql(cond: str) -> str:
    """Pairs x < y of candidates of the index, either of which is one of the other's."""
    return f"""{index_sql().replace("b.rank) AS k", "b.id) AS k")},
pairs AS (SELECT DISTINCT least(x, y) AS x, greatest(x, y) AS y FROM (SELECT x, unnest(near) AS y FROM c))
SELECT pairs.x, pairs.y, len(list_filter({cond}, lambda z: z <> pairs.x AND z <> pairs.y AND a.ds[z] < a.ds[pairs.y] AND b.ds[z] < a.ds[pairs.y])) AS n
FROM pairs JOIN p a ON a.x = pairs.x JOIN p b ON b.x = pairs.y"""


def _lune(between: bool) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Witnesses of every pair of candidates of the index, counted."""
        ranked = Setup(spark, sf_dir).ranked
        near = _by_rank(ranked, frontier.exact_knn(ranked, SMALL.spatial)).withColumn("far", F.lit(False))
        near = near.union(index.window_pairs(ranked, SMALL.window).where("src < dst").withColumn("far", F.lit(True)))
        # of a pair that comes as a spatial neighbour the end that has it as one goes first: few lie nearer to it
        once = near.groupBy(F.least("src", "dst"), F.greatest("src", "dst")).agg(F.min(F.struct("far", "src", "dst")).alias("e"))
        pairs = materialise(once.select(F.col("e.src").alias("x"), F.col("e.dst").alias("y")), "pairs")
        return frontier.lune_counts(ranked, pairs, between).select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y"), "n")

    return run


_named("range_lune_counts", _lune_sql("range(pairs.x + 1, pairs.y)"), _lune(True))
_named("lune_counts", _lune_sql("range(1, len(a.ds) + 1)"), _lune(False))


@registered(f"{index_sql().replace('b.rank) AS k', 'b.id) AS k')} SELECT src, dst FROM graph")
def reused_knn_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The index built on a k-NN graph that is there already."""
    ranked = Setup(spark, sf_dir).ranked
    near = materialise(_by_rank(ranked, frontier.exact_knn(ranked, SMALL.spatial)), "knn")
    return index.edges(index.build(ranked, SMALL, knn_graph=near)).select(F.col("src_rank").alias("src"), F.col("dst_rank").alias("dst"))


@registered(_KNN)
def stored_without_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Graph and entry pointers are stored by shard, vectors come back from the objects."""
    s = Setup(spark, sf_dir)
    path = posixpath.join(index.checkpoint_root(spark), "rangeknn", uuid.uuid4().hex)
    index.save(s.built(rows=200), path, vectors=False)
    return shown(index.search(index.load(spark, path, s.ranked, 200), s.queries, graph_kernel(LARGE_EF)))


@registered(f"""{scan_graph_sql()},
walk(x, y, spot, hops) AS (
  SELECT rank, 1 + rank * 7919 % n, rank, 0::BIGINT FROM r, n
  UNION ALL
  SELECT w.x, w.y, arg_min(g.dst, {{'d': t.ds[g.dst], 'r': g.dst}}), w.hops + 1 FROM walk w JOIN graph g ON g.src = w.spot JOIN p t ON t.x = w.y WHERE w.spot <> w.y GROUP BY w.x, w.y, w.spot, w.hops, t.ds[w.spot]
  HAVING min(t.ds[g.dst]) < t.ds[w.spot])
SELECT x, y, max(hops) AS hops, bool_or(spot = y) AS reached FROM walk GROUP BY x, y""")
def greedy_walks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From every object a greedy walk on the exact graph to one stored target."""
    ranked = Setup(spark, sf_dir).ranked
    n = ranked.count()
    graph = materialise(exact.between_graph(ranked), "graph")
    return frontier.greedy_paths(ranked, graph, ranked.select(F.col("rank").alias("x"), (F.col("rank") * 7919 % n + 1).alias("y")))


_NEAREST = f"""WITH {E_SQL} SELECT src, dst FROM (SELECT a.id AS src, b.id AS dst, row_number() OVER (PARTITION BY a.id ORDER BY list_distance(a.vec, b.vec), b.id) AS k FROM r a JOIN r b ON a.id <> b.id) WHERE k <= 16"""


@registered(_NEAREST)
def knn_graph_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frontier.exact_knn(Setup(spark, sf_dir).ranked, 16, shard_rows=1_024).select("src", "dst")


@registered(None)
def knn_graph_bucketed_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of the bucketed graph against the exact one."""
    ranked = Setup(spark, sf_dir).ranked
    return metrics.edge_coverage(frontier.bucketed_knn(ranked, 16, cell_rows=64, copies=3), frontier.exact_knn(ranked, 16).select("src", "dst"))


_INSIDE = E_SQL.replace("r AS (", "whole AS (") + ", r AS (SELECT * REPLACE (rank - 100 AS rank) FROM whole WHERE rank BETWEEN 101 AND 300)"


@registered(f"{index_sql(_INSIDE)} SELECT src + 100 AS src, dst + 100 AS dst FROM graph")
def rebuild_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The index rebuilt within ranks 101-300, both candidate sources made anew."""
    part = Setup(spark, sf_dir).ranked.where(F.col("rank").between(101, 300))
    return index.edges(index.build(part, SMALL, 1 << 20)).select(F.col("src_rank").alias("src"), F.col("dst_rank").alias("dst"))


@registered(f"WITH {E_SQL} SELECT i - 1 AS pos, round(avg(v), 6) AS mean FROM (SELECT unnest(vec) AS v, generate_subscripts(vec, 1) AS i FROM r) GROUP BY i")
def centroid(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = index.global_centroid(Setup(spark, sf_dir).ranked)
    return spark.createDataFrame(list(enumerate(c)), "pos bigint, mean double").select("pos", F.round("mean", 6).alias("mean"))


@registered(f"""WITH {E_SQL}, c AS (SELECT list(m ORDER BY i) AS centre FROM (SELECT i, avg(v) AS m FROM (SELECT unnest(vec) AS v, generate_subscripts(vec, 1) AS i FROM r) GROUP BY i)),
x AS (SELECT rank, list_distance(vec, centre) AS d FROM r, c),
len AS (SELECT b.rank, count(*) AS n FROM x a JOIN x b ON a.rank <= b.rank AND NOT EXISTS (SELECT 1 FROM x z WHERE z.rank > a.rank AND z.rank <= b.rank AND z.d <= a.d) GROUP BY b.rank),
e AS (SELECT count(*) AS n FROM r)
SELECT (SELECT n FROM e) AS nodes, sum(n)::BIGINT AS header_ids, round(sum(n) / (SELECT n FROM e), 6) AS mean_ids, 4 * (SELECT n FROM e) AS header_bytes FROM len""")
def header_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.header_stats(Setup(spark, sf_dir).built(kernels.Params(4, 4, 8))).select("nodes", "header_ids", "mean_ids", "header_bytes")


_GAPS = f"""WITH i AS ({index_sql()} SELECT src, dst FROM graph), x AS ({scan_graph_sql()} SELECT src, dst FROM graph), c AS ({index_sql()} SELECT x AS src, unnest(near) AS dst FROM c),
a AS (SELECT i.src IS NOT NULL AS i, x.src IS NOT NULL AS x, c.src IS NOT NULL AS c FROM i FULL JOIN x ON i.src = x.src AND i.dst = x.dst
 LEFT JOIN c ON c.src = coalesce(i.src, x.src) AND c.dst = coalesce(i.dst, x.dst)),
n AS (SELECT count(*) FILTER (i AND x) AS shared, count(*) FILTER (x AND NOT i AND NOT c) AS endpoint_absent, count(*) FILTER (x AND NOT i AND c) AS crowded_out, count(*) FILTER (i AND NOT x) AS witness_absent FROM a)
SELECT *, round(shared / (shared + endpoint_absent + crowded_out), 6) AS recall, round(shared / (shared + witness_absent), 6) AS precision FROM n"""


@registered(_GAPS)
def gap_breakdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Why the index differs from the exact graph."""
    s = Setup(spark, sf_dir)
    own = index.edges(s.built()).select(F.col("src_rank").alias("src"), F.col("dst_rank").alias("dst"))
    ids = s.ranked.select("id", "rank")
    near = frontier.exact_knn(s.ranked, SMALL.spatial).join(ids.select(F.col("id").alias("src"), F.col("rank").alias("a")), "src").join(ids.select(F.col("id").alias("dst"), F.col("rank").alias("b")), "dst")
    cand = near.select(F.col("a").alias("src"), F.col("b").alias("dst")).union(index.window_pairs(s.ranked, SMALL.window)).distinct()
    return metrics.gap_breakdown(own, exact.between_graph(s.ranked), cand)


_STEP = 250


@registered(f"""WITH b AS (SELECT lang AS method, n_chars // {_STEP} AS step, count(*) AS n, count(*) FILTER (toxic = 1) AS hits FROM documents JOIN labels USING (doc_id)
 WHERE lang IS NOT NULL AND n_chars IS NOT NULL GROUP BY ALL),
c AS (SELECT method, (sum(hits) OVER w)::DOUBLE / (sum(hits) OVER (PARTITION BY method))::DOUBLE AS recall, (sum(n) OVER w)::DOUBLE AS cost
 FROM b WHERE method IN (SELECT method FROM b WHERE hits > 0) WINDOW w AS (PARTITION BY method ORDER BY step DESC ROWS UNBOUNDED PRECEDING)),
s AS (SELECT *, lag(recall) OVER w AS r0, lag(cost) OVER w AS c0 FROM c WINDOW w AS (PARTITION BY method ORDER BY recall, cost DESC))
SELECT method, round(min(CASE WHEN recall >= 0.95 AND r0 IS NULL THEN cost WHEN recall >= 0.95 AND r0 < 0.95 THEN c0 + (0.95 - r0) * (cost - c0) / (recall - r0) END), 6) AS cost, max(recall) AS max_recall FROM s GROUP BY method""")
def cost_at_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cost at a recall between two measured points: how many labelled documents of a language are read, longest first in steps
    of a length, until so large a share of its toxic ones is found."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.col("lang").alias("method"), F.expr(f"n_chars div {_STEP}").alias("step"))
    both = docs.where("method is not null and step is not null").join(table(spark, sf_dir, "labels").select("doc_id", "toxic"), "doc_id")
    steps = both.groupBy("method", "step").agg(F.count("*").alias("n"), F.count(F.when(F.col("toxic") == 1, 1)).alias("hits"))
    so_far = Window.partitionBy("method").orderBy(F.desc("step")).rowsBetween(Window.unboundedPreceding, 0)
    sums = steps.select("method", F.sum("hits").over(so_far).alias("hits"), F.sum("n").over(so_far).cast("double").alias("cost"), F.sum("hits").over(Window.partitionBy("method")).alias("all"))
    curve = sums.where(F.col("all") > 0).select("method", (F.col("hits") / F.col("all")).alias("recall"), "cost")
    return metrics.interpolated(curve, 0.95).select("method", F.round("cost", 6).alias("cost"), "max_recall")


# Experiments: every setting of a sweep is a query id of its own, so a method needs one job.

BASE = 1_000


Setting = tuple[str, int, int]  # label of the share, ef, k


def swept(s: Setup, shares: list[float | None], efs: list[int], ks: tuple[int, ...]) -> tuple[DataFrame, list[Setting]]:
    """The held-out queries under every setting: qid is qid * BASE + place of the setting.

    Hashed ids keep their low 52 bits, so that the product fits; smaller ids stay as they are.
    """
    asked, settings, out = s.queries.select("qid", "qvec"), [], None
    for share in shares:
        label = "mixed" if share is None else f"{share:g}"
        mine = [(label, ef, k) for ef in efs for k in ks]
        codes = F.array(*(F.struct(F.lit(len(settings) + i).cast("bigint").alias("place"), F.lit(k).alias("k")) for i, (_, _, k) in enumerate(mine)))
        settings += mine
        one = intervals(s.ranked, asked, share).select("qid", "qvec", "lo", "hi", F.explode(codes).alias("c"))
        one = one.select((F.col("qid").bitwiseAND(F.lit((1 << 52) - 1)) * BASE + F.col("c.place")).alias("qid"), "qvec", "lo", "hi", F.col("c.k").alias("k"))
        out = one if out is None else out.unionByName(one)
    return materialise(out, "sweep"), settings


def by_setting(found: DataFrame, truth: DataFrame, settings: list[Setting], method: str) -> DataFrame:
    """(method, share, ef, k, recall, n_dist) of one method; queries without an answer count as recall 0."""
    spark = found.sparkSession
    names = F.broadcast(spark.createDataFrame([(i, s, ef, k) for i, (s, ef, k) in enumerate(settings)], "place bigint, share string, ef bigint, k bigint"))
    cost = found.groupBy("qid").agg(F.max("n_dist").alias("n_dist"))
    n = truth.groupBy("qid").agg(F.count("*").alias("n"))
    hits = found.select("qid", "id").join(truth.select("qid", "id"), ["qid", "id"]).groupBy("qid").agg(F.count("*").alias("hits"))
    each = n.join(hits, "qid", "left").join(cost, "qid", "left").withColumn("place", F.pmod("qid", F.lit(BASE)))
    per = each.groupBy("place").agg(F.round(F.avg(F.coalesce("hits", F.lit(0)) / F.col("n")), 4).alias("recall"), F.round(F.avg(F.coalesce("n_dist", F.lit(0))), 1).alias("n_dist"))
    return per.join(names, "place").select(F.lit(method).alias("method"), "share", "ef", "k", "recall", "n_dist")


def truth_of(packed: DataFrame, queries: DataFrame, settings: list[Setting]) -> DataFrame:
    """(qid, id) of the exact answers of every setting; settings that differ by the pool only share one scan."""
    base: dict[tuple[str, int], int] = {}
    twins = [(base.setdefault((share, k), i), i) for i, (share, _, k) in enumerate(settings)]
    names = packed.sparkSession.createDataFrame(twins, "base bigint, place bigint")
    mine = F.pmod("qid", F.lit(BASE))
    once = index.search(packed, queries.where(mine.isin(sorted(base.values())))).select("qid", "id", mine.alias("base"))
    return materialise(once.join(F.broadcast(names), "base").select((F.col("qid") - F.col("base") + F.col("place")).alias("qid"), "id"), "truth")


def together(jobs: dict[str, Callable[[], DataFrame]], at_once: int = 6) -> dict[str, DataFrame]:
    """The jobs' tables; jobs that leave cores idle run beside each other."""
    with ThreadPoolExecutor(at_once) as pool:
        running = {name: pool.submit(job) for name, job in jobs.items()}
        return {name: r.result() for name, r in running.items()}


def experiment(s: Setup, methods: dict[str, tuple[DataFrame, Callable]], shares: list[float | None], efs: list[int], ks: tuple[int, ...] = (10,)) -> DataFrame:
    """Every method at every share, pool and k: a table of recall and distance computations."""
    queries, settings = swept(s, shares, efs, ks)
    pools = [ef for _, ef, _ in settings]
    truth = truth_of(s.packed(), queries, settings)
    asked = lambda packed, make: lambda: materialise(index.search(packed, queries, make(lambda qid: pools[qid % BASE])), "found")
    out = None
    for name, found in together({n: asked(*how) for n, how in methods.items()}).items():
        one = by_setting(found, truth, settings, name)
        out = one if out is None else out.unionByName(one)
    return materialise(out, "experiment")


def walking(entry: str = "header", through: bool = False) -> Callable:
    """Beam search whose pool depends on the query's id."""
    return lambda ef: lambda sh, q, lo, hi, k, qid: graph_kernel(ef(qid), entry, through=through)(sh, q, lo, hi, k, qid // BASE)


def structure(make: Callable) -> Callable:
    return lambda ef: multi_range.per_shard(make, ef)


def contenders(s: Setup) -> dict[str, tuple[DataFrame, Callable]]:
    """The index and the methods of comparison, as (stored shards, kernel by pool)."""
    built, spatial, packed = s.built(), s.built(kernels.Params(16, 0, 32, prune="spatial")), s.packed()
    files = lambda ef: index.builds(lambda sh, q, lo, hi, k, qid, made={}: _probe(made, sh, q, lo, hi, k, ef(qid)))
    return {
        "index": (built, walking()),
        "segment tree": (packed, structure(baselines.SegmentTree)),
        "segment bitmap": (packed, structure(multi_range.SegmentBitmap)),
        "range covers": (packed, lambda ef: multi_range.per_shard(lambda v: multi_range.StoredRanges(v, "covers"), ef, lazy=True)),
        "compressed, max leap": (packed, structure(multi_range.CompressedRanges)),
        "rectangle labels": (packed, structure(multi_range.RectangleRanges)),
        "dense predicate": (packed, lambda ef: _masked(ef)),
        "inverted file": (packed, files),
        "auto placement": (built, lambda ef: lambda sh, q, lo, hi, k, qid: baselines.auto_kernel(ef=ef(qid))(sh, q, lo, hi, k, qid)),
        "layered graph, in-filter": (packed, lambda ef: _layered(ef)),
        "spatial graph, in-filter": (spatial, walking()),
        "post-filter": (spatial, lambda ef: lambda sh, q, lo, hi, k, qid: baselines.post_kernel(4, True, ef(qid))(sh, q, lo, hi, k, qid)),
    }


def _made_once(make: Callable) -> Callable:
    """make(shard), kept for as long as queries ask the same shard."""
    held: dict = {}

    def get(sh: index.Shard):
        key = int(sh.ids[0])
        if key not in held:
            held.clear()
            held[key] = make(sh)
        return held[key]

    return get


def _masked(ef: Callable) -> Callable:
    graph = _made_once(lambda sh: baselines.DensePredicateGraph(sh.vecs))

    def run(sh: index.Shard, q, lo: int, hi: int, k: int, qid: int):
        passes = np.zeros(len(sh.ids), bool)
        passes[lo : hi + 1] = True
        return (*graph(sh).search(q, passes, k, ef(qid)), 0)

    return index.builds(run)


def _layered(ef: Callable) -> Callable:
    """Not marked as building: its queries walk so much that they are dealt to tasks, each of which makes the layers again."""
    graph = _made_once(lambda sh: baselines.Layered(sh.vecs, sh.ids))

    def run(sh: index.Shard, q, lo: int, hi: int, k: int, qid: int):
        g = graph(sh)
        return kernels.beam(g.start, g.nbrs, sh.vecs, q, lo, hi, k, ef(qid), g.entry(q), through=True)

    return run


def _curve(name: str) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        s = Setup(spark, sf_dir, name)
        return experiment(s, contenders(s), [None, 0.01, 0.1, 0.5], [10, 20, 40, 80, 160])

    return run


_named("experiment_curve_approx", None, _curve("E"))
_named("experiment_curve_documents_approx", None, _curve("D"))


def _probe(made: dict, s: index.Shard, q, lo: int, hi: int, k: int, ef: int):
    key = int(s.ids[0])
    if key not in made:
        made.clear()
        made[key] = baselines.InvertedFile(s.vecs)
    got, work = made[key].search(q, lo, hi, k, max(1, ef // 10), ef)
    return got, work, 0


@registered(None)
def experiment_parameters_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Degree cap and window against recall and cost by share, and realised degree."""
    s = Setup(spark, sf_dir)
    kinds = [(8, 32), (16, 32), (32, 32), (64, 32), (32, 0), (32, 8), (32, 64), (32, 128)]
    made = together({f"m {m}, window {window}": lambda how=kernels.Params(16, window, m): s.built(how) for m, window in kinds})
    got = experiment(s, {n: (built, walking()) for n, built in made.items()}, [0.01, 0.1, 0.5, None], [20, 80])
    out = None
    for name, built in made.items():
        one = got.where(F.col("method") == name).join(metrics.degree_stats(built).select("mean_degree", "bytes"), F.lit(True))
        out = one if out is None else out.unionByName(one)
    return out


@registered(None)
def experiment_ablation_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The greatest recall over a sweep of pools for each construction and share, with its distances, and whether 0.98 is met."""
    s = Setup(spark, sf_dir, "D")
    kinds = {"index": SMALL, "no window": kernels.Params(16, 0, 32), "spatial prune": kernels.Params(16, 32, 32, prune="spatial"), "neither": kernels.Params(16, 0, 32, prune="spatial")}
    curve = experiment(s, {n: (built, walking()) for n, built in together({n: lambda how=how: s.built(how) for n, how in kinds.items()}).items()}, [0.01, 0.1, 0.5], [10, 40, 160, 400])
    best = curve.groupBy("method", "share").agg(F.max("recall").alias("max_recall"), F.max_by("n_dist", "recall").alias("n_dist"))
    return best.withColumn("reaches", F.col("max_recall") >= 0.98)


@registered(None)
def experiment_entry_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entry policies on the same index."""
    s = Setup(spark, sf_dir)
    built = s.built()
    return experiment(s, {e: (built, walking(e)) for e in ("header", "first", "random", "centre")}, [0.05, 0.1, 0.5], [10, 20, 40])


@registered(None)
def experiment_k_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Larger result lists at a tenth of the objects."""
    s = Setup(spark, sf_dir)
    return experiment(s, {"index": (s.built(), walking()), "segment tree": (s.packed(), structure(baselines.SegmentTree))}, [0.1], [100, 200], (20, 40, 70, 100))


@registered(None)
def experiment_two_attributes_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Box index against one-attribute graphs that test the second attribute while searching."""
    b = Boxes(spark, sf_dir)
    built = b.built()
    truth = materialise(multi.box_search(built, b.queries, multi.box_scan), "truth")
    out = None
    for ef in (20, 80):
        kinds = {"box index": multi.box_kernel(ef), "box index, no fallback": multi.box_kernel(ef, False), "compressed": multi_range.per_shard(multi_range.CompressedRanges, ef), "segment tree": multi_range.per_shard(baselines.SegmentTree, ef)}
        for name, kernel in kinds.items():
            one = measured(multi.box_search(built, b.queries, kernel), truth).select(F.lit(name).alias("method"), F.lit(ef).alias("ef"), "recall", "n_dist")
            out = one if out is None else out.unionByName(one)
    return out


@registered(None)
def experiment_scaling_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Object tables of different sizes, up to all line items, under mixed intervals with a pool of 40: recall, distances and median
    microseconds of a query in one kernel, seconds of the whole build job, degree and bytes."""
    out = None
    for name in ("E", "T", "D", "V"):
        s = Setup(spark, sf_dir, name, None)
        packed = materialise(s.packed(), "shards")
        centre, began = index.global_centroid(s.ranked), time.perf_counter()
        built = index.build_packed(packed, SMALL, centre)
        took = round(time.perf_counter() - began, 2)
        truth = materialise(index.search(packed, s.queries), "truth")
        found = materialise(index.search(built, s.queries, index.timed(graph_kernel(40))), "found")
        each = found.groupBy("qid").agg(F.sum("n_hops").alias("us")).agg(F.percentile("us", 0.5).alias("median_us"))
        one = measured(found, truth).select(F.lit(name).alias("objects"), "queries", "recall", "n_dist", F.lit(took).alias("build_s"))
        for more in (each, metrics.degree_stats(built)):
            one = one.join(materialise(more, "measure"), F.lit(True))
        out = one if out is None else out.unionByName(one)
    return out


@registered(None)
def experiment_structures_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Build seconds, edges a node and bytes of the index and of the methods of comparison, all built from the same shards."""
    packed = Setup(spark, sf_dir).packed()

    def graph(how: kernels.Params) -> Callable:
        def make(sh: index.Shard) -> tuple[int, int]:
            start, nbrs = kernels.build(sh.vecs, how)
            return len(nbrs), 4 * (len(nbrs) + len(start))

        return make

    kinds = {
        "segment tree": baselines.SegmentTree,
        "segment bitmap": multi_range.SegmentBitmap,
        "compressed, max leap": multi_range.CompressedRanges,
        "rectangle labels": multi_range.RectangleRanges,
        "dense predicate": baselines.DensePredicateGraph,
        "inverted file": baselines.InvertedFile,
    }
    makers = {n: lambda sh, c=c: multi_range.footprint(c(sh.vecs)) for n, c in kinds.items()}
    makers |= {"layered graph": lambda sh: multi_range.footprint(baselines.Layered(sh.vecs, sh.ids)), "index": graph(SMALL), "spatial graph": graph(kernels.Params(16, 0, 32, prune="spatial"))}
    got = materialise(index.structure_report(packed, makers), "structures").groupBy("method")
    return got.agg(F.sum("nodes").alias("nodes"), F.round(F.sum("seconds"), 3).alias("seconds"), F.round(F.sum("edges") / F.sum("nodes"), 2).alias("mean_degree"), F.sum("bytes").alias("bytes"))


# Streams and windows over events.


@registered("SELECT (date_trunc('day', ts) - INTERVAL 12 HOUR * s + CASE WHEN s = 0 AND hour(ts) >= 12 THEN INTERVAL 12 HOUR ELSE INTERVAL 0 HOUR END + CASE WHEN s = 1 AND hour(ts) >= 12 THEN INTERVAL 12 HOUR ELSE INTERVAL 0 HOUR END) AS window_start, count(*) AS n FROM events, (VALUES (0), (1)) t(s) WHERE ts IS NOT NULL GROUP BY ALL")
def sliding_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events in windows of a day that start every half day."""
    e = table(spark, sf_dir, "events").withColumn("at", F.col("ts").cast("timestamp"))
    return e.groupBy(F.window("at", "1 day", "12 hours").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("window_start"), "n")


@registered("""WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM g)
SELECT user_id, min(ts) AS session_start, count(*) AS n FROM s GROUP BY user_id, session""")
def session_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of each user: events less than six hours apart."""
    e = table(spark, sf_dir, "events").withColumn("at", F.col("ts").cast("timestamp"))
    return e.groupBy("user_id", F.session_window("at", "6 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("session_start"), "n")


@registered("SELECT date_trunc('day', ts) AS window_start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The day counts as a stream that runs to completion."""
    schema = table(spark, sf_dir, "events").schema
    source = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    root = posixpath.join(index.checkpoint_root(spark), "rangeknn", uuid.uuid4().hex)
    keep = lambda batch, n: batch.write.mode("overwrite").parquet(f"{root}/counts")
    query = stream.tumbling_counts(source).writeStream.outputMode("complete").option("checkpointLocation", f"{root}/state").foreachBatch(keep).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.read.parquet(f"{root}/counts").select(F.col("window_start").cast("timestamp_ntz").alias("window_start"), "event_type", "n")
