"""Registered queries of the operators around arrays, with DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import ArrayQuery, Constraint
from ..operators import query as Q
from ..operators import tables as T
from ..operators.linear import chunk_coords, with_chunks
from ..operators.tree import IndexConfig, build_index
from ..streaming import append as S
from .arrays import ARRAYS, cells_and_spec, index_of, load, where_sql
from .stream_queries import sliced

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}
_AE, _A2 = ARRAYS["ae"].sql, ARRAYS["a2"].sql
_IN_CHUNKS = f'WITH c AS (SELECT *, min("user") OVER () AS l0, min(hour) OVER () AS l1 FROM ({_AE})), k AS (SELECT "user", hour, value, ("user" - l0) // 16 AS c0, (hour - l1) // 16 AS c1, ("user" - l0) % 16 * 16 + (hour - l1) % 16 AS cell_no FROM c) '


def query(sql: str):
    def put(f):
        QUERIES[f.__name__], SQL[f.__name__] = f, sql
        return f

    return put


_SOME = where_sql("a2", "value >= 20000.0 AND value <= 30000.0")
_BOX = where_sql("a2", "partkey >= 33 AND partkey < 129 AND suppkey >= 5")


@query(f"SELECT *, 'both' AS side FROM (({_SOME}) INTERSECT ({_BOX})) UNION ALL SELECT *, 'value only' AS side FROM (({_SOME}) EXCEPT ({_BOX}))")
def set_ops(spark: SparkSession, d: str) -> DataFrame:
    """Answers of two queries, met and subtracted."""
    index = index_of(spark, d, "a2")
    by_value = Q.range_query(index, ArrayQuery({}, Constraint.between(20000.0, 30000.0, hi_incl=True)))
    by_box = Q.range_query(index, ArrayQuery({"partkey": Constraint.between(33, 129), "suppkey": Constraint.at_least(5)}))
    return by_value.intersect(by_box).withColumn("side", F.lit("both")).unionByName(by_value.exceptAll(by_box).withColumn("side", F.lit("value only")))


_BOXES = [(0, 0, 40, 100, 300), (1, 30, 90, 0, 17), (2, -20, 5, 650, 5000), (3, 17, 17, 0, 100)]


@query(_IN_CHUNKS.rstrip() + f", b(box, lo0, hi0, lo1, hi1) AS (VALUES {', '.join(map(str, _BOXES))}), g AS (SELECT c0, c1, min(l0) AS l0, min(l1) AS l1, count(*) AS n_cells FROM k, (SELECT min(l0) AS l0, min(l1) AS l1, max(\"user\") AS m0, max(hour) AS m1 FROM c) GROUP BY 1, 2) SELECT box, c0, c1, n_cells FROM b JOIN g ON lo0 < hi0 AND lo1 < hi1 AND greatest(lo0, l0) < l0 + 16 * (c0 + 1) AND hi0 > l0 + 16 * c0 AND greatest(lo1, l1) < l1 + 16 * (c1 + 1) AND hi1 > l1 + 16 * c1")
def overlap_boxes(spark: SparkSession, d: str) -> DataFrame:
    cells, spec = cells_and_spec(spark, d, "ae")
    return T.overlap_boxes(spark.createDataFrame(_BOXES, "box long, lo_user long, hi_user long, lo_hour long, hi_hour long"), cells, spec)


@query(f'WITH h AS (SELECT *, CASE WHEN hour = lag(hour) OVER (PARTITION BY "user" ORDER BY hour) + 1 THEN 0 ELSE 1 END AS fresh FROM ({_AE}) WHERE value >= 20.0), r AS (SELECT *, sum(fresh) OVER (PARTITION BY "user" ORDER BY hour ROWS UNBOUNDED PRECEDING) AS run FROM h) SELECT "user", min(hour) AS "first", max(hour) AS "last", count(*) AS length FROM r GROUP BY "user", run')
def value_runs(spark: SparkSession, d: str) -> DataFrame:
    cells, spec = cells_and_spec(spark, d, "ae")
    return T.value_runs(cells, spec, F.col("value") >= 20.0)


@query(f'SELECT "user", hour, max(value) OVER (PARTITION BY "user" ORDER BY hour ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS peak, first_value(hour) OVER (PARTITION BY "user" ORDER BY hour ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS began FROM ({_AE})')
def row_frames(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user").orderBy("hour").rowsBetween(-2, 2)
    return cells_and_spec(spark, d, "ae")[0].select("user", "hour", F.max("value").over(w).alias("peak"), F.first("hour").over(w).alias("began"))


@query(_IN_CHUNKS + "SELECT c0, c1, bit_or(CAST(1 AS BIGINT) << (cell_no % 62)) AS some, bit_xor(CAST(1 AS BIGINT) << (cell_no % 62)) AS odd, bit_and(cell_no) AS shared FROM k GROUP BY 1, 2")
def bit_aggregates(spark: SparkSession, d: str) -> DataFrame:
    cells, spec = cells_and_spec(spark, d, "ae")
    bit = F.expr("shiftleft(1L, cast(cell_no % 62 as int))")
    return with_chunks(cells, spec).withColumns({f"c{i}": c for i, c in enumerate(chunk_coords(spec))}).groupBy("c0", "c1").agg(F.bit_or(bit).alias("some"), F.bit_xor(bit).alias("odd"), F.bit_and("cell_no").alias("shared"))


@query(_IN_CHUNKS + "SELECT c0, c1, count(DISTINCT value) AS n_values, count(DISTINCT hour) AS n_hours FROM k GROUP BY 1, 2")
def distinct_values(spark: SparkSession, d: str) -> DataFrame:
    cells, spec = cells_and_spec(spark, d, "ae")
    return cells.groupBy(*(c.alias(f"c{i}") for i, c in enumerate(chunk_coords(spec)))).agg(F.countDistinct("value").alias("n_values"), F.countDistinct("hour").alias("n_hours"))


@query(_IN_CHUNKS + "SELECT c0, c1, quantile_disc(value, 0.5) AS middle, quantile_disc(value, 0.9) AS high FROM k GROUP BY 1, 2")
def chunk_quantiles(spark: SparkSession, d: str) -> DataFrame:
    """Exact order statistics of each chunk; chunks are bounded."""
    cells, spec = cells_and_spec(spark, d, "ae")
    at = lambda p: F.expr(f"percentile_disc({p}) WITHIN GROUP (ORDER BY value)")
    return cells.groupBy(*(c.alias(f"c{i}") for i, c in enumerate(chunk_coords(spec)))).agg(at(0.5).alias("middle"), at(0.9).alias("high"))


@query("SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2 HAVING count(*) >= 2")
def value_maps(spark: SparkSession, d: str) -> DataFrame:
    """Per user a map event type -> number, filtered as a map and unfolded again. A map has one entry for each type."""
    counts = load(spark, d, "events").groupBy("user_id", "event_type").count()
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m"))
    return maps.select("user_id", F.explode(F.map_filter("m", lambda _, n: n >= 2)).alias("event_type", "n"))


@query(_IN_CHUNKS + "SELECT c0, c1, cell_no FROM k")
def payload_positions(spark: SparkSession, d: str) -> DataFrame:
    """Cell numbers into one bitmap for each chunk (an aggregate), and out of it again (a table function)."""
    cells, spec = cells_and_spec(spark, d, "ae")
    maps = with_chunks(cells, spec).withColumns({f"c{i}": c for i, c in enumerate(chunk_coords(spec))}).groupBy("c0", "c1").agg(T.bitmap_of("cell_no").alias("payload"))
    return maps.lateralJoin(T.BitmapPositions(F.col("payload").outer())).select("c0", "c1", "cell_no")


@query(where_sql("ae", '"user" >= 20 AND "user" < 90 AND value > 30.0'))
def source_range(spark: SparkSession, d: str) -> DataFrame:
    """A written index through the data source, with filters that prune its leaves."""
    from ..sources.index_source import register

    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    register(spark)
    path = S.fresh_folder(spark, "index")
    build_index(*cells_and_spec(spark, d, "ae"), IndexConfig(), path)
    return spark.read.format("gridmask").option("index", path).load().where("user >= 20 and user < 90 and value > 30.0")


_JOINED = f"SELECT partkey, suppkey, a.value, b.value AS quantity FROM ({_A2}) a JOIN ({ARRAYS['a2q'].sql}) b USING (partkey, suppkey)"


def _by_join(how: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda s, d: T.hinted_join(cells_and_spec(s, d, "a2")[0], cells_and_spec(s, d, "a2q")[0].withColumnRenamed("value", "quantity"), ["partkey", "suppkey"], how)


for _how in ("shuffle_hash", "merge"):
    QUERIES[f"array_join_{_how}"], SQL[f"array_join_{_how}"] = _by_join(_how), _JOINED


@query("SELECT event_id, user_id, value FROM events")
def stream_dedup(spark: SparkSession, d: str) -> DataFrame:
    """Each slice is delivered with all its rows twice; every event arrives once."""
    first, path, events = sliced(spark, d, copies=2)
    stream = S.deduplicated(S.event_stream(spark, path, events)).select("event_id", "user_id", "value")
    return S.run_to_files(stream, path + "-out", S.fresh_folder(spark, "stream-checkpoint")).unionByName(first.select("event_id", "user_id", "value"))


_BANDS = [("low", 0, 50, 40.0), ("middle", 40, 100, 60.0), ("none", 10, 5, 0.0)]


@query(f"SELECT band, event_id, value FROM events JOIN (VALUES {', '.join(map(str, _BANDS))}) b(band, lo, hi, least) ON user_id >= lo AND user_id < hi AND value >= least")
def stream_static_range(spark: SparkSession, d: str) -> DataFrame:
    """Standing range queries (a small static table) over events as they come."""
    first, path, events = sliced(spark, d)
    first.drop("h").coalesce(1).write.mode("append").parquet(path)
    bands = spark.createDataFrame(_BANDS, "band string, lo long, hi long, least double")
    hits = S.standing_queries(S.event_stream(spark, path, events, files=2), bands)
    return S.run_to_files(hits.select("band", "event_id", "value"), path + "-out", S.fresh_folder(spark, "stream-checkpoint"))


@query('WITH c AS ({}), k AS (SELECT *, min(turn) OVER () AS l FROM c) SELECT conv, turn - (turn - l) % 8 AS turn_from, {} FROM k GROUP BY 1, 2'.format(ARRAYS["ac"].sql, ", ".join(f"max(value) FILTER (WHERE (turn - l) % 8 = {k}) AS t{k}" for k in range(8))))
def pivot_turns(spark: SparkSession, d: str) -> DataFrame:
    """Every turn of every conversation, eight to a row; pivot_dim tells the first three turns only."""
    cells, spec = cells_and_spec(spark, d, "ac")
    return T.pivot_blocks(cells, spec, "turn", "t")


@query(f'WITH c AS ({_AE}), g AS (SELECT DISTINCT "user", h.hour FROM c, (SELECT unnest(generate_series((SELECT min(hour) FROM c), (SELECT max(hour) FROM c))) AS hour) h) SELECT g."user", g.hour, c.value AS latest FROM g ASOF JOIN c ON g."user" = c."user" AND g.hour >= c.hour')
def asof_hours(spark: SparkSession, d: str) -> DataFrame:
    """The latest value of every user at every hour of the array; asof_cell asks for one hour in 24 of 30 days only."""
    cells, spec = cells_and_spec(spark, d, "ae")
    return T.as_of_all(cells, spec, "hour")
