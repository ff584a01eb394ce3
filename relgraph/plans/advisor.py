"""Which estimator fits which needs, from published star scores (1 to 4) and memory order; the needs are given, or those of a graph's sources."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from relgraph.model import UncertainGraph
from relgraph.operators.kernels import MOST_EDGES

# Method, then stars for variance, accuracy, time, memory.
STARS = (
    ("mc", 1, 3, 2, 4), ("bitmap", 1, 3, 1, 2), ("tree", 1, 3, 3, 3), ("skip", 1, 3, 3, 4), ("split", 4, 4, 4, 1), ("strata", 4, 4, 4, 1),
)
# Index, then stars for build time, load time, update time, size.
INDEX_STARS = (("bitmap", 4, 3, 1, 3), ("tree", 3, 4, 4, 4))
CRITERIA = ("variance", "accuracy", "time", "memory")
#: From the least memory to the most.
MEMORY_ORDER = ("mc", "skip", "tree", "bitmap", "split", "strata")
#: A source none of whose edges is likelier than this has few hits, whose estimates spread widely against their mean.
UNLIKELY = 0.5
NEEDS = ("low_variance", "tight_memory")


def scores(spark: SparkSession) -> DataFrame:
    """(method, criterion, stars, place): stars as rows, with each criterion's dense rank."""
    wide = spark.createDataFrame(list(STARS), ["method", *CRITERIA])
    long = wide.unpivot("method", list(CRITERIA), "criterion", "stars")
    return long.selectExpr("method", "criterion", "CAST(stars AS INT) AS stars", "CAST(dense_rank() OVER (PARTITION BY criterion ORDER BY stars DESC) AS INT) AS place")


def index_scores(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(INDEX_STARS), "method string, build int, load int, update int, size int")


def scores_sql() -> str:
    rows = ", ".join(f"('{m}', '{c}', {s})" for m, *v in STARS for c, s in zip(CRITERIA, v, strict=True))
    return f"""SELECT method, criterion, CAST(stars AS INTEGER) AS stars, CAST(dense_rank() OVER (PARTITION BY criterion ORDER BY stars DESC) AS INTEGER) AS place
FROM (VALUES {rows}) v(method, criterion, stars)"""


def _methods(spark: SparkSession, may_index: bool) -> DataFrame:
    rows = [(m, *v) for m, *v in STARS if may_index or m not in ("bitmap", "tree")]
    if may_index:
        rows += [(f"tree+{m}", *v[:2], v[2] + 1, v[3]) for m, *v in STARS if m in ("split", "strata")]
    return spark.createDataFrame(rows, ["method", *CRITERIA])


def _weights(fast: bool) -> dict:
    """The weight of each criterion, from the needs in columns."""
    return {
        "variance": F.when(F.col("low_variance"), 2).otherwise(0), "accuracy": F.lit(1), "time": F.lit(2 if fast else 1), "memory": F.when(F.col("tight_memory"), 3).otherwise(0),
    }


def _placed(kinds: DataFrame, may_index: bool, fast: bool) -> DataFrame:
    """(low_variance, tight_memory, method, score, place) for every kind of needs."""
    score = sum((F.col(c) * w for c, w in _weights(fast).items()), F.lit(0)).alias("score")
    placed = F.rank().over(Window.partitionBy(*NEEDS).orderBy(F.desc("score"))).cast("int").alias("place")
    return kinds.crossJoin(_methods(kinds.sparkSession, may_index)).select(*NEEDS, "method", score).select("*", placed)


def recommend(spark: SparkSession, low_variance: bool = False, tight_memory: bool = False, may_index: bool = True, fast: bool = True) -> DataFrame:
    """(method, score, place): methods by the stars of the criteria that matter.

    With an index allowed, coupling the tree with a recursive method is scored too: it has that method's
    variance and accuracy, at least its speed, and its memory.
    """
    kind = spark.createDataFrame([(low_variance, tight_memory)], "low_variance boolean, tight_memory boolean")
    return _placed(kind, may_index, fast).select("method", "score", "place")


def needs(g: UncertainGraph, most: int = MOST_EDGES) -> DataFrame:
    """(s, low_variance, tight_memory) of every source: whether its edges are all unlikely, and whether the graph has more
    edges than are sent whole to a worker."""
    size = g.edges.agg((F.count("*") > most).alias("tight_memory"))
    return g.edges.groupBy(F.col("src").alias("s")).agg((F.max("prob") < UNLIKELY).alias("low_variance")).crossJoin(size)


def needs_scores(needs: DataFrame) -> DataFrame:
    """(low_variance, tight_memory, sources, method, criterion, weight, stars, place): `scores` beside each kind of needs that
    sources have, with how many have it and what weight it gives the criterion."""
    weight = F.coalesce(*(F.when(F.col("criterion") == c, w) for c, w in _weights(True).items())).alias("weight")
    kinds = needs.groupBy(*NEEDS).agg(F.count("*").alias("sources"))
    return kinds.crossJoin(scores(needs.sparkSession)).select(*NEEDS, "sources", "method", "criterion", weight, "stars", "place")


def needs_recommend(needs: DataFrame, may_index: bool = True, fast: bool = True) -> DataFrame:
    """(s, low_variance, tight_memory, method, score, place): `recommend` for the needs of every source."""
    kinds = needs.sparkSession.createDataFrame([(v, m) for v in (False, True) for m in (False, True)], "low_variance boolean, tight_memory boolean")
    return needs.join(F.broadcast(_placed(kinds, may_index, fast)), list(NEEDS)).select("s", *NEEDS, "method", "score", "place")


def _needs_sql(graph: str) -> str:
    return f"""g AS ({graph}),
needs AS (SELECT src AS s, max(prob) < {UNLIKELY} AS low_variance, (SELECT count(*) FROM g) > {MOST_EDGES} AS tight_memory FROM g GROUP BY src)"""


def needs_scores_sql(graph: str) -> str:
    return f"""WITH {_needs_sql(graph)}, kinds AS (SELECT low_variance, tight_memory, count(*) AS sources FROM needs GROUP BY ALL)
SELECT low_variance, tight_memory, sources, method, criterion, CAST(CASE criterion WHEN 'variance' THEN CASE WHEN low_variance THEN 2 ELSE 0 END
  WHEN 'accuracy' THEN 1 WHEN 'time' THEN 2 ELSE CASE WHEN tight_memory THEN 3 ELSE 0 END END AS INTEGER) AS weight, stars, place FROM kinds, ({scores_sql()})"""


def needs_recommend_sql(graph: str) -> str:
    """Where an index is allowed and speed counts."""
    rows = ", ".join(f"('{m}', {', '.join(map(str, v))})" for m, *v in STARS)
    return f"""WITH {_needs_sql(graph)}, one AS (SELECT * FROM (VALUES {rows}) v(method, variance, accuracy, time, memory)),
every AS (SELECT * FROM one UNION ALL SELECT 'tree+' || method, variance, accuracy, time + 1, memory FROM one WHERE method IN ('split', 'strata')),
scored AS (SELECT low_variance, tight_memory, method, CAST(CASE WHEN low_variance THEN 2 ELSE 0 END * variance + accuracy + 2 * time + CASE WHEN tight_memory THEN 3 ELSE 0 END * memory AS BIGINT) AS score
  FROM every, (SELECT DISTINCT low_variance, tight_memory FROM needs)),
placed AS (SELECT *, CAST(rank() OVER (PARTITION BY low_variance, tight_memory ORDER BY score DESC) AS INTEGER) AS place FROM scored)
SELECT s, low_variance, tight_memory, method, score, place FROM needs JOIN placed USING (low_variance, tight_memory)"""
