"""More of what a user writes around the methods: joins by strategy, set operations, recall tables, formats,
stateful streams, and the checks and measures that need the index."""

from __future__ import annotations

import posixpath
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from rangeknn.functions import vectors
from rangeknn.operators import baselines, exact, frontier, index, kernels, metrics, multi_range
from rangeknn.operators.index import graph_kernel, materialise
from rangeknn.plans.methods import by_setting, structure, swept, together, truth_of, walking
from rangeknn.plans.surface import registered
from rangeknn.plans.workload import E_SQL, LARGE_EF, SMALL, Setup, index_sql, intervals_sql, measured, shown
from rangeknn.sources import files
from rangeknn.sources.catalog import table
from rangeknn.streaming import stream

Query = Callable[[SparkSession, str], DataFrame]


def _named(name: str, sql: str | None, run: Query) -> None:
    run.__name__ = name
    registered(sql)(run)


# Sources, joins, distances.


@registered("SELECT vec_id, len(embedding)::INT AS dim, label FROM embeddings")
def scan_embeddings(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select("vec_id", F.size("embedding").alias("dim"), "label")


def broadcast_attach(vecs: DataFrame, attrs: DataFrame, key: str, most: int = 1_000_000) -> DataFrame:
    """vecs joined with attrs by broadcasts of at most about ``most`` rows: the smaller side if it is that small, or else the
    attributes in slices by a hash of the key."""
    n, rows = attrs.count(), vecs.count()
    if n > most and rows <= most:
        return F.broadcast(vecs).join(attrs, key)
    slices = max(1, -(-n // most))
    out = None
    for i in range(slices):
        part = attrs if slices == 1 else attrs.where(F.pmod(F.xxhash64(key), F.lit(slices)) == i)
        one = vecs.join(F.broadcast(part), key)
        out = one if out is None else out.union(one)
    return out


def _attach(how: str) -> Query:
    """Vectors with a price; the hint names the join. The broadcast form bounds what is broadcast."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        price = table(spark, d, "orders").select(F.col("o_orderkey").alias("vec_id"), "o_totalprice")
        vecs = table(spark, d, "embeddings").select("vec_id", "label")
        return broadcast_attach(vecs, price, "vec_id") if how == "broadcast" else vecs.join(price.hint(how), "vec_id")

    return run


for _how in ("broadcast", "merge", "shuffle_hash"):
    _named(f"attach_attr_{_how}", "SELECT vec_id, label, o_totalprice FROM embeddings JOIN orders ON vec_id = o_orderkey", _attach(_how))


@registered("""SELECT a.vec_id, round(list_distance(a.embedding::DOUBLE[], z.embedding::DOUBLE[]), 6) AS l2, round(list_inner_product(a.embedding::DOUBLE[], z.embedding::DOUBLE[]), 6) AS dot,
round(pow(list_distance(a.embedding::DOUBLE[], z.embedding::DOUBLE[]), 2), 6) AS l2_sq FROM embeddings a, embeddings z WHERE z.vec_id = 1""")
def dist_functions(spark: SparkSession, d: str) -> DataFrame:
    """Distances to one vector: the column functions."""
    e = table(spark, d, "embeddings")
    one = e.where("vec_id = 1").select(F.col("embedding").alias("q"))
    v, q = F.col("embedding"), F.col("q")
    near = e.join(F.broadcast(one), F.lit(True))
    return near.select("vec_id", F.round(vectors.l2(v, q), 6).alias("l2"), F.round(vectors.dot(v, q), 6).alias("dot"), F.round(vectors.l2_sq(v, q), 6).alias("l2_sq"))


_KNN = f"""WITH {E_SQL}, {intervals_sql()}, d AS (SELECT qid, id, list_distance(vec, qvec) AS dist FROM q JOIN r ON attr BETWEEN lo AND hi)
SELECT qid, rn, id, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rn FROM d) WHERE rn <= 10"""


@registered(_KNN)
def knn_join_range(spark: SparkSession, d: str) -> DataFrame:
    s = Setup(spark, d)
    return shown(exact.knn_join(s.ranked, s.queries, 10))


@registered(f"WITH {E_SQL}, {intervals_sql('0.5')}, s AS (SELECT (rank - 1) // 100 AS shard, min(attr) AS a, max(attr) AS b FROM r GROUP BY ALL) SELECT qid, count(*) AS shards FROM q JOIN s ON b >= lo AND a <= hi GROUP BY qid")
def shard_overlap(spark: SparkSession, d: str) -> DataFrame:
    """How many shards of 100 ranks each query is routed to."""
    s = Setup(spark, d, share=0.5)
    directory = s.packed(100).select(F.col("lo").alias("a"), F.col("hi").alias("b"))
    return s.queries.join(F.broadcast(directory), (F.col("b") >= F.col("lo")) & (F.col("a") <= F.col("hi"))).groupBy("qid").agg(F.count("*").alias("shards"))


# Windows without a window over all rows.


@registered(f"WITH {E_SQL} SELECT id, ntile(7) OVER (ORDER BY rank) AS segment FROM r")
def ntile_segments(spark: SparkSession, d: str) -> DataFrame:
    """Seven segments of equal count, by arithmetic on the ranks."""
    ranked = Setup(spark, d).ranked
    n = ranked.count()
    low, wide = n // 7, n % 7
    inside = (F.col("rank") - 1) < wide * (low + 1)
    first = F.floor((F.col("rank") - 1) / (low + 1))
    rest = F.lit(wide) + F.floor((F.col("rank") - 1 - wide * (low + 1)) / max(low, 1))
    return ranked.select("id", (F.when(inside, first).otherwise(rest) + 1).cast("bigint").alias("segment"))


@registered(f"""WITH {E_SQL}, c AS (SELECT list(m ORDER BY i) AS centre FROM (SELECT i, avg(v) AS m FROM (SELECT unnest(vec) AS v, generate_subscripts(vec, 1) AS i FROM r) GROUP BY i))
SELECT rank, round(min(list_distance(vec, centre)) OVER (ORDER BY rank), 6) AS least FROM r, c""")
def running_min_centroid(spark: SparkSession, d: str, run: int = 4_096) -> DataFrame:
    """The least distance to the centroid up to each rank: minima within runs of ranks, then over the runs before."""
    ranked = Setup(spark, d).ranked
    centre = F.array(*(F.lit(v) for v in index.global_centroid(ranked)))
    x = ranked.select("rank", F.floor((F.col("rank") - 1) / run).alias("run"), vectors.l2(F.col("vec"), centre).alias("dist"))
    before = Window.orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
    carry = x.groupBy("run").agg(F.min("dist").alias("m")).select("run", F.min("m").over(before).alias("carry"))
    here = F.min("dist").over(Window.partitionBy("run").orderBy("rank"))
    return x.withColumn("here", here).join(carry, "run").select("rank", F.round(F.least("here", "carry"), 6).alias("least"))


# Candidate and edge sets.

_NEAR = "near AS (SELECT src, dst FROM (SELECT a.rank AS src, b.rank AS dst, row_number() OVER (PARTITION BY a.rank ORDER BY list_distance(a.vec, b.vec), b.id) AS k FROM r a JOIN r b ON a.id <> b.id) WHERE k <= 8)"
_WINDOW = "(SELECT a.rank AS src, b.rank AS dst FROM r a JOIN r b ON b.rank BETWEEN a.rank - 8 AND a.rank + 8 AND a.rank <> b.rank)"


@registered(f"WITH {E_SQL}, {_NEAR} SELECT src, dst FROM near UNION {_WINDOW}")
def cand_union(spark: SparkSession, d: str) -> DataFrame:
    """Spatial and window candidates together, by rank."""
    ranked = Setup(spark, d).ranked
    place = ranked.select("id", "rank")
    near = frontier.exact_knn(ranked, 8).select("src", "dst")
    near = near.join(place.toDF("src", "a"), "src").join(place.toDF("dst", "b"), "dst").select(F.col("a").alias("src"), F.col("b").alias("dst"))
    return near.union(index.window_pairs(ranked, 8)).distinct()


def _edges(s: Setup, **how) -> DataFrame:
    return index.edges(s.built(**how)).select(F.col("src_rank").alias("src"), F.col("dst_rank").alias("dst"))


def _against_window(op: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        s = Setup(spark, d)
        return getattr(_edges(s), op)(index.window_pairs(s.ranked, 8))

    return run


_named("edge_intersect", f"{index_sql()} SELECT src, dst FROM graph INTERSECT {_WINDOW}", _against_window("intersect"))
_named("edge_except", f"{index_sql()} SELECT src, dst FROM graph EXCEPT {_WINDOW}", _against_window("exceptAll"))


def ten_intervals(s: Setup) -> list[tuple[int, int, int]]:
    """(number, first rank, last rank) of ten intervals of a tenth of the ranks each, by the workload rule."""
    n = s.ranked.count()
    w = max(1, n // 10)
    return [(i, 1 + i * 7919 % (n - w + 1), i * 7919 % (n - w + 1) + w) for i in range(10)]


#: Edges of ``graph`` within the ten intervals, with the number of differences there must be.
INSIDE_SQL = """, i AS (SELECT unnest(range(0, 10)) AS i), w AS (SELECT greatest(1, n // 10) AS w, n FROM n),
parts AS (SELECT 1 + i * 7919 % (n - w + 1) AS r_lo, i * 7919 % (n - w + 1) + w AS r_hi FROM i, w)
SELECT r_lo, r_hi, 0::BIGINT AS n, count(src) AS edges FROM parts LEFT JOIN graph ON src BETWEEN r_lo AND r_hi AND dst BETWEEN r_lo AND r_hi GROUP BY r_lo, r_hi"""


def same_inside(s: Setup, graph: DataFrame, again: Callable[[int, int], DataFrame]) -> DataFrame:
    """(r_lo, r_hi, n, edges): by how many edges ``again(first, last)`` differs from the graph's part inside, for ten intervals."""
    out = None
    for _, lo, hi in ten_intervals(s):
        inside = exact.induce(graph, lo, hi)
        n = exact.difference(inside, again(lo, hi)).agg(F.count("*").alias("n"))
        row = n.join(inside.agg(F.count("*").alias("edges")), F.lit(True)).select(F.lit(lo).cast("bigint").alias("r_lo"), F.lit(hi).cast("bigint").alias("r_hi"), "n", "edges")
        out = row if out is None else out.union(row)
    return out


@registered(f"{index_sql()}{INSIDE_SQL}")
def restriction_diff(spark: SparkSession, d: str) -> DataFrame:
    """For ten intervals, candidates cut to their ranks before the prune give the index's own edges inside: no difference, among so many."""
    s = Setup(spark, d)
    centre = index.global_centroid(s.ranked)
    packed = materialise(s.packed(), "shards")
    ranks = lambda built: index.edges(built).select(F.col("src_rank").alias("src"), F.col("dst_rank").alias("dst"))
    whole = materialise(ranks(index.build_packed(packed, SMALL, centre)), "edges")
    return same_inside(s, whole, lambda lo, hi: ranks(index.build_packed(packed, SMALL, centre, (lo, hi))))


@registered(f"{index_sql()} SELECT 0::BIGINT AS n, count(*) AS edges FROM graph")
def missing_links(spark: SparkSession, d: str) -> DataFrame:
    """No consecutive ranks lack an edge, so the index is strongly connected inside every interval."""
    s = Setup(spark, d)
    own = _edges(s)
    return exact.missing_links(own, s.ranked).agg(F.count("*").alias("n")).join(own.agg(F.count("*").alias("edges")), F.lit(True))


# Recall tables.

_HITS = f"""WITH {E_SQL}, {intervals_sql()}, h AS (SELECT qid, qid % 4 AS part, qid % 3 AS turn, least(10, count(*)) AS hits FROM q JOIN r ON attr BETWEEN lo AND hi GROUP BY qid)"""


def _recalls(spark: SparkSession, d: str) -> DataFrame:
    s = Setup(spark, d)
    truth, found = index.search(s.packed(), s.queries), index.search(s.built(), s.queries, graph_kernel(LARGE_EF))
    r = metrics.recall_at_k(found, truth, 10)
    return r.withColumn("part", F.col("qid") % 4).withColumn("turn", F.col("qid") % 3)


def _sums(grouped) -> DataFrame:
    return grouped.agg(F.count("*").alias("queries"), F.sum("hits").cast("bigint").alias("hits"), F.round(F.avg("recall"), 6).alias("recall"))


_SUMS = "count(*) AS queries, sum(hits)::BIGINT AS hits, round(avg(hits / 10), 6) AS recall"
_named("recall_cube", f"{_HITS} SELECT part, turn, {_SUMS} FROM h GROUP BY CUBE (part, turn)", lambda spark, d: _sums(_recalls(spark, d).cube("part", "turn")))
_named("recall_grouping_sets", f"{_HITS} SELECT part, turn, {_SUMS} FROM h GROUP BY GROUPING SETS ((part), (turn), ())", lambda spark, d: _sums(_recalls(spark, d).groupingSets([["part"], ["turn"], []], "part", "turn")))
_named("recall_summary", f"{_HITS} SELECT {_SUMS}, round(min(hits / 10), 6) AS worst FROM h", lambda spark, d: _recalls(spark, d).agg(F.count("*").alias("queries"), F.sum("hits").cast("bigint").alias("hits"), F.round(F.avg("recall"), 6).alias("recall"), F.round(F.min("recall"), 6).alias("worst")))


# Scalars: JSON, arrays, approximate counts.


@registered("SELECT event_id, CAST(json_extract(props, '$.k') AS INT) AS k FROM events WHERE CAST(json_extract(props, '$.k') AS INT) >= 50")
def json_props_filter(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")).where("k >= 50")


@registered("SELECT user_id, list(value ORDER BY value DESC, event_id) AS top FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS n FROM events) WHERE n <= 3 GROUP BY user_id")
def array_topk(spark: SparkSession, d: str) -> DataFrame:
    """The three largest values of each user as an array; lists are cut before they are gathered."""
    best = Window.partitionBy("user_id").orderBy(F.desc("value"), "event_id")
    few = table(spark, d, "events").withColumn("n", F.row_number().over(best)).where("n <= 3")
    return few.groupBy("user_id").agg(F.sort_array(F.collect_list("value"), asc=False).alias("top"))


@registered(None)
def approx_distinct_attr(spark: SparkSession, d: str) -> DataFrame:
    """Distinct prices by sketch, next to the exact number."""
    o = table(spark, d, "orders")
    return o.agg(F.approx_count_distinct("o_totalprice", 0.01).alias("about"), F.count_distinct("o_totalprice").alias("exact"))


@registered("""WITH c AS (SELECT label, list(m ORDER BY i) AS centre FROM (SELECT label, i, avg(v) AS m FROM (SELECT label, unnest(embedding::DOUBLE[]) AS v, generate_subscripts(embedding, 1) AS i FROM embeddings) GROUP BY ALL) GROUP BY label)
SELECT vec_id, arg_min(c.label, {'d': list_distance(embedding::DOUBLE[], centre), 'l': c.label}) AS cell FROM embeddings, c GROUP BY vec_id""")
def ivf_cells(spark: SparkSession, d: str) -> DataFrame:
    """The cell of each vector: the nearest of the labels' centroids, whose number is checked."""
    e = table(spark, d, "embeddings")
    means = e.select("label", F.posexplode("embedding").alias("pos", "v")).groupBy("label", "pos").agg(F.avg(F.col("v").cast("double")).alias("m"))
    cells = means.groupBy("label").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "m"))), lambda s: s["m"]).alias("centre"))
    if cells.count() > 65_536:
        raise ValueError("over 65,536 cells")
    near = e.select("vec_id", "embedding").join(F.broadcast(cells), F.lit(True))
    at = F.struct(vectors.l2(F.col("embedding"), F.col("centre")), F.col("label"))
    return near.groupBy("vec_id").agg(F.min_by("label", at).alias("cell"))


# Formats.


def _round_trip(fmt: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        few = Setup(spark, d).ranked.select("id", "attr", "rank")
        path = posixpath.join(index.checkpoint_root(spark), "rangeknn", uuid.uuid4().hex)
        files.write(few, path, fmt)
        return files.read(spark, path, few.schema, fmt)

    return run


for _fmt in files.FORMATS:
    _named(f"{_fmt}_round_trip", f"WITH {E_SQL} SELECT id, attr, rank FROM r", _round_trip(_fmt))


# Streams with state.


def _events(spark: SparkSession, d: str, copies: int = 1) -> DataFrame:
    """The events as a stream, from files of their own so that there are several batches."""
    e = table(spark, d, "events")
    made = e
    for _ in range(copies - 1):
        made = made.unionByName(e)
    path = materialise(made.repartition(3, "user_id"), "events").inputFiles()[0].rsplit("/", 1)[0]
    return spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 4).parquet(path)


@registered("""WITH o AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS n FROM events WHERE ts IS NOT NULL AND user_id IS NOT NULL)
SELECT user_id, list(event_id ORDER BY n) FILTER (n <= 5) AS ids, count(*) AS n_seen FROM o GROUP BY user_id""")
def stream_recent(spark: SparkSession, d: str) -> DataFrame:
    """The last five events of each user, kept as state of a stream."""
    rows = stream.drained(stream.recent(_events(spark, d), ttl_ms=400 * 86_400_000), "update")
    return rows.groupBy("user_id").agg(F.max_by("ids", "batch").alias("ids"), F.max_by("n_seen", "batch").alias("n_seen"))


@registered("SELECT event_id, user_id FROM events")
def stream_fresh(spark: SparkSession, d: str) -> DataFrame:
    """Every event comes twice and is kept once."""
    return stream.drained(stream.fresh(_events(spark, d, 2)), "append").select("event_id", "user_id")


@registered("""SELECT a.user_id, a.event_id AS left_id, b.event_id AS right_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR
WHERE a.event_type = 'view' AND b.event_type = 'purchase'""")
def stream_followed_by(spark: SparkSession, d: str) -> DataFrame:
    """Purchases within six hours of a view of the same user, as a join of two streams."""
    one, two = (_events(spark, d).where(F.col("event_type") == t) for t in ("view", "purchase"))
    return stream.drained(stream.followed_by(one, two, "user_id", "6 hours"), "append").select("user_id", "left_id", "right_id")


# Further methods and experiments.


@registered(None)
def hashing_approx(spark: SparkSession, d: str) -> DataFrame:
    """Recall of bucketed random projections under the interval."""
    s = Setup(spark, d)
    truth = index.search(s.packed(), s.queries)
    return metrics.recall_at_k(baselines.hashed_search(s.ranked, s.queries), truth, 10).agg(F.count("*").alias("queries"), F.round(F.avg("recall"), 4).alias("recall"))


@registered(None)
def experiment_build_approx(spark: SparkSession, d: str) -> DataFrame:
    """Seconds of the k-NN graph and of the prune, edges a node, for caps and windows that share one k-NN graph."""
    hows = [kernels.Params(16, w, m) for m, w in ((8, 32), (16, 32), (32, 32), (64, 32), (32, 0), (32, 8), (32, 64), (32, 128))]
    names = spark.createDataFrame([(i, h.m, h.window) for i, h in enumerate(hows)], "setting bigint, m int, window int")
    got = materialise(index.build_report(Setup(spark, d).packed(), hows), "build_report").groupBy("setting")
    got = got.agg(F.sum("nodes").alias("nodes"), F.round(F.sum("edges") / F.sum("nodes"), 3).alias("mean_degree"), F.round(F.sum("knn_s"), 3).alias("knn_s"), F.round(F.sum("prune_s"), 3).alias("prune_s"))
    return got.join(F.broadcast(names), "setting").select("m", "window", "nodes", "mean_degree", "knn_s", "prune_s")


@registered(None)
def experiment_tuned_approx(spark: SparkSession, d: str, target: float = 0.95) -> DataFrame:
    """The smallest pool that reaches the target on half of the queries, with recall and cost on the other half."""
    s = Setup(spark, d)
    queries, settings = swept(s, [0.1], [10, 20, 40, 80, 160], (10,))
    truth = truth_of(s.packed(), queries, settings)
    spatial, packed = kernels.Params(16, 0, 32, prune="spatial"), s.packed()
    kinds = {
        "index": (s.built(), walking()),
        "spatial graph, in-filter": (s.built(spatial), walking()),
        "spatial graph with repair, in-filter": (s.built(kernels.Params(16, 0, 32, prune="spatial", repair=True)), walking()),
        "segment tree, fan-out 2": (packed, structure(lambda v: baselines.SegmentTree(v))),
        "segment tree, fan-out 8": (packed, structure(lambda v: baselines.SegmentTree(v, fanout=8))),
    }
    halves: list[DataFrame | None] = [None, None]
    for name, (built, make) in kinds.items():
        found = materialise(index.search(built, queries, make(lambda qid: settings[qid % 1_000][1])), "found")
        for half in (0, 1):
            mine = F.pmod(F.floor(F.col("qid") / 1_000), F.lit(2)) == half
            one = by_setting(found.where(mine), truth.where(mine), settings, name).select("method", "ef", "recall", "n_dist")
            halves[half] = one if halves[half] is None else halves[half].unionByName(one)
    return metrics.tuned(halves[0], halves[1], target)


@registered(None)
def prefilter_graph_approx(spark: SparkSession, d: str) -> DataFrame:
    """Recall and distances of a graph made for each query's interval; its build is not counted as distances."""
    s = Setup(spark, d)
    return measured(baselines.pre_filter(s.packed(), s.queries, "graph"), s.truth())


@registered(None)
def experiment_rate_approx(spark: SparkSession, d: str, target: float = 0.95) -> DataFrame:
    """Queries a second of one kernel thread where recall meets the target, for several k at a tenth of the objects.

    A query's time is the median over the queries of a setting, so making a structure at the first query of a shard
    does not count. ratio: rate over that of the segment tree; null where a method does not reach the target.
    """
    s = Setup(spark, d)
    queries, settings = swept(s, [0.1], [10, 20, 40, 80, 160, 320], (10, 20, 40, 70, 100))
    truth = truth_of(s.packed(), queries, settings)
    packed = s.packed()
    kinds = {
        "index": (s.built(), walking()),
        "spatial graph, in-filter": (s.built(kernels.Params(16, 0, 32, prune="spatial")), walking()),
        "compressed, max leap": (packed, structure(multi_range.CompressedRanges)),
        "rectangle labels": (packed, structure(multi_range.RectangleRanges)),
        "segment tree": (packed, structure(lambda v: baselines.SegmentTree(v))),
    }
    names = spark.createDataFrame([(i, ef, k) for i, (_, ef, k) in enumerate(settings)], "place bigint, ef bigint, k bigint")
    curve = None
    asked = lambda built, make: lambda: materialise(index.search(built, queries, index.timed(make(lambda qid: settings[qid % 1_000][1]))), "found")
    for name, found in together({n: asked(*how) for n, how in kinds.items()}).items():
        each = found.groupBy("qid").agg(F.max("n_hops").alias("us")).groupBy(F.pmod("qid", F.lit(1_000)).alias("place")).agg(F.percentile("us", 0.5).alias("cost"))
        one = by_setting(found, truth, settings, name).join(each.join(F.broadcast(names), "place"), ["ef", "k"])
        one = one.select(F.concat_ws("|", "method", "k").alias("method"), "recall", "cost")
        curve = one if curve is None else curve.unionByName(one)
    at = metrics.interpolated(materialise(curve, "curve"), target)
    parts = F.split("method", "[|]")
    rate = at.select(parts[0].alias("method"), parts[1].cast("int").alias("k"), F.round(F.lit(1e6) / F.col("cost"), 1).alias("qps"), "max_recall")
    base = F.max(F.when(F.col("method") == "segment tree", F.col("qps"))).over(Window.partitionBy("k"))
    return rate.withColumn("ratio", F.round(F.col("qps") / base, 3))


# More streams: late rows, quality of results, an index that grows.


@registered("""WITH a AS (SELECT *, event_id % 2 AS batch FROM events), h AS (SELECT max(epoch_us(ts)) AS high FROM a WHERE batch = 0)
SELECT batch, count(*) AS n_rows, count(*) FILTER (batch = 1 AND epoch_us(ts) < high - 86400000000) AS late FROM a, h GROUP BY batch""")
def stream_late_rows(spark: SparkSession, d: str) -> DataFrame:
    """Events of even ids come first, then the others; those more than a day behind what was seen are late."""
    root = posixpath.join(index.checkpoint_root(spark), "rangeknn", uuid.uuid4().hex)
    e = table(spark, d, "events")
    for part in (0, 1):
        e.where(F.col("event_id") % 2 == part).coalesce(1).write.mode("append").parquet(f"{root}/in")
    source = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(f"{root}/in")
    stream.late_rows(source, 86_400, root).awaitTermination()
    return spark.read.schema("n_rows bigint, late bigint, batch bigint").parquet(f"{root}/rows").select("batch", "n_rows", "late")


_T_SQL = E_SQL.replace("o_totalprice::DOUBLE", "epoch_us(ts)::DOUBLE").replace("orders ON vec_id = o_orderkey", "events ON vec_id = event_id")


@registered(f"""WITH {_T_SQL}, {intervals_sql()}, h AS (SELECT qid, any_value(lo) AS lo, least(10, count(*)) AS hits FROM q JOIN r ON attr BETWEEN lo AND hi GROUP BY qid)
SELECT date_trunc('day', make_timestamp(lo::BIGINT)) AS window_start, count(*) AS queries, sum(hits)::BIGINT AS hits, round(avg(hits / 10), 6) AS recall FROM h GROUP BY 1""")
def stream_quality(spark: SparkSession, d: str) -> DataFrame:
    """Recall by the day at which a query's interval begins, from results that come as a stream."""
    s = Setup(spark, d, "T")
    found = metrics.recall_at_k(index.search(s.built(), s.queries, graph_kernel(LARGE_EF)), s.truth(), 10)
    at = s.queries.select("qid", F.timestamp_micros(F.col("lo").cast("bigint")).alias("at"))
    rows = materialise(found.join(at, "qid").select("at", "hits", "recall").repartition(3), "results")
    source = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(rows.inputFiles()[0].rsplit("/", 1)[0])
    got = stream.drained(stream.quality_windows(source), "complete")
    return got.where(F.col("batch") == got.agg(F.max("batch")).first()[0]).drop("batch")


@registered(_KNN)
def stream_append_search(spark: SparkSession, d: str) -> DataFrame:
    """Objects come in several batches, each a segment of the index; queries ask all of them."""
    s = Setup(spark, d)
    root = posixpath.join(index.checkpoint_root(spark), "rangeknn", uuid.uuid4().hex)
    rows = materialise(s.ranked.select("id", "vec", "attr").repartition(3, "id"), "objects")
    source = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(rows.inputFiles()[0].rsplit("/", 1)[0])
    stream.append_stream(source, root, SMALL).awaitTermination()
    return shown(stream.search_segments(spark, root, s.queries, graph_kernel(LARGE_EF)))
