"""What the registered workloads share: ranked objects with their queries, and the same in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangeknn.operators import index, kernels, metrics
from rangeknn.operators.index import materialise
from rangeknn.sources.catalog import held_out, intervals, objects

#: Parameters for tables of a few hundred to a few thousand objects.
SMALL = kernels.Params(spatial=16, window=32, m=32)
LARGE_EF = 1_000_000


class Setup:
    """Ranked objects and interval queries of one object table."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str = "E", share: float | None = 0.1, k: int = 10) -> None:
        objs, asked = held_out(index.validate(objects(spark, sf_dir, name)))
        self.ranked = materialise(index.with_rank(objs), "ranked")
        self.queries = materialise(intervals(self.ranked, asked, share, k), "queries")

    def packed(self, rows: int = index.SHARD_ROWS) -> DataFrame:
        return index.shards(self.ranked, rows)

    def truth(self) -> DataFrame:
        return index.search(self.packed(), self.queries)

    def built(self, how: kernels.Params = SMALL, rows: int = index.SHARD_ROWS) -> DataFrame:
        return index.build(self.ranked, how, rows)


def shown(found: DataFrame) -> DataFrame:
    return found.select("qid", "rn", "id", F.round(F.sqrt("d2"), 6).alias("dist"))



def measured(found: DataFrame, truth: DataFrame, k: int = 10) -> DataFrame:
    """One row: queries, recall, distances and expanded nodes a query of an approximate answer."""
    found = materialise(found, "found")
    cost = found.groupBy("qid").agg(F.max("n_dist").alias("n_dist"), F.max("n_hops").alias("n_hops"))
    each = metrics.recall_at_k(found, truth, k, "min_k_truth").join(cost, "qid", "left")
    mean = lambda c, places: F.round(F.avg(F.coalesce(c, F.lit(0))), places).alias(c)
    return each.agg(F.count("*").alias("queries"), mean("recall", 4), mean("n_dist", 1), mean("n_hops", 1))


E_SQL = """o AS (SELECT vec_id AS id, embedding::DOUBLE[] AS vec, o_totalprice::DOUBLE AS attr FROM embeddings JOIN orders ON vec_id = o_orderkey),
r AS (SELECT *, row_number() OVER (ORDER BY attr, id) AS rank FROM o WHERE id % 25 <> 7)"""


def intervals_sql(share: str = "0.1") -> str:
    return f"""w AS (SELECT id AS qid, vec AS qvec, greatest(1, floor({share} * n))::BIGINT AS w, n FROM o, (SELECT count(*) AS n FROM r) WHERE id % 25 = 7),
q AS (SELECT qid, qvec, a.attr AS lo, b.attr AS hi FROM (SELECT *, 1 + (qid * 7919) % (n - w + 1) AS r1 FROM w) JOIN r a ON a.rank = r1 JOIN r b ON b.rank = r1 + w - 1)"""


def scan_graph_sql(cand: str = "", cap: str = "", base: str = "") -> str:
    """Two-sided witness scan by rank gap as a recursive table; cand restricts, cap bounds."""
    return f"""WITH RECURSIVE {base or E_SQL},
p AS MATERIALIZED (SELECT a.rank AS x, list(list_distance(a.vec, b.vec) ORDER BY b.rank) AS ds FROM r a, r b GROUP BY a.rank),
n AS (SELECT count(*) AS n FROM r){cand},
scan(x, side, g, kept) AS (
  SELECT rank, side, 0, []::BIGINT[] FROM r, (VALUES (-1), (1)) s(side)
  UNION ALL
  SELECT s.x, side, g + 1, CASE WHEN {"NOT list_contains(c.near, s.x + side * (g + 1)) OR " if cand else ""}{cap}len(list_filter(kept, lambda z: a.ds[z] < a.ds[s.x + side * (g + 1)] AND b.ds[z] < a.ds[s.x + side * (g + 1)])) > 0 THEN kept ELSE list_append(kept, s.x + side * (g + 1)) END
  FROM scan s JOIN p a ON a.x = s.x JOIN p b ON b.x = s.x + side * (g + 1){" JOIN c ON c.x = s.x" if cand else ""}),
graph AS (SELECT x AS src, unnest(kept) AS dst FROM (SELECT x, side, max_by(kept, g) AS kept FROM scan GROUP BY x, side))"""


_CAND = """,
near AS (SELECT x, y FROM (SELECT a.rank AS x, b.rank AS y, row_number() OVER (PARTITION BY a.rank ORDER BY list_distance(a.vec, b.vec), b.rank) AS k FROM r a JOIN r b ON a.rank <> b.rank) WHERE k <= 16),
c AS MATERIALIZED (SELECT x, list(DISTINCT y) AS near FROM (SELECT x, y FROM near UNION SELECT a.rank, b.rank FROM r a JOIN r b ON b.rank BETWEEN a.rank - 32 AND a.rank + 32 AND a.rank <> b.rank) GROUP BY x)"""


def index_sql(base: str = "") -> str:
    """The index with the settings of SMALL over the ranked objects of ``base``."""
    return scan_graph_sql(_CAND, "len(kept) >= 16 OR ", base)
