"""Queries around the simulation: slicing, joining, reporting and storing agents
and the tables they come from.  Each has SQL of the same meaning beside it.

Windows go by lane or by block of an axis; the few that rank a whole class do so on
pre-aggregated or limited rows."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import models
from .functions import surface
from .operators import runtime, space, visible
from .operators.tick import naive_sql
from .sources.adapters import EXTENTS, ORACLE, cents, read

QUERIES: dict = {}
SQL: dict[str, str] = {}
FISH, CARS, PREY = ORACLE["fish"], ORACLE["vehicle"], ORACLE["prey"]
KINDS = ("click", "error", "purchase", "signup", "view")


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql is not None:
            SQL[key] = sql
        return f

    return add


def fish(s: SparkSession, d: str) -> DataFrame:
    return EXTENTS["fish"](s, d)


def cars(s: SparkSession, d: str) -> DataFrame:
    return EXTENTS["vehicle"](s, d)


def bigint(x):
    return x.cast("bigint")


# -- projections, filters, nulls ------------------------------------------------
@query(f"SELECT id, vx * vx + vy * vy AS speed2, CASE WHEN x < 30000 THEN 'west' WHEN x < 70000 THEN 'middle' ELSE 'east' END AS side FROM ({FISH}) WHERE y BETWEEN 1000 AND 9000 AND informed IN (0, 1, 2, 3)")
def q_project_filter(s, d):
    side = F.when(F.col("x") < 30_000, "west").when(F.col("x") < 70_000, "middle").otherwise("east")
    return fish(s, d).where(F.col("y").between(1000, 9000) & F.col("informed").isin(0, 1, 2, 3)).select("id", (F.col("vx") * F.col("vx") + F.col("vy") * F.col("vy")).alias("speed2"), side.alias("side"))


@query(f"SELECT id, informed FROM ({FISH}) WHERE informed <= 1")
def q_informed_only(s, d):
    return fish(s, d).where("informed <= 1").select("id", "informed")


@query("SELECT count(*) FILTER (WHERE quality IS NOT DISTINCT FROM toxic) AS same, count(*) FILTER (WHERE quality IS DISTINCT FROM toxic) AS other FROM documents LEFT JOIN labels USING (doc_id)")
def q_nullsafe(s, d):
    both = read(s, d, "documents").select("doc_id").join(read(s, d, "labels").select("doc_id", "quality", "toxic"), "doc_id", "left")
    same = F.col("quality").eqNullSafe(F.col("toxic"))
    return both.agg(F.count_if(same).alias("same"), F.count_if(~same).alias("other"))


@query("SELECT source, count(*) AS n, count(*) FILTER (WHERE toxic IS NULL) AS unlabelled, CAST(sum(coalesce(toxic, 0)) AS BIGINT) AS toxic FROM documents LEFT JOIN labels USING (doc_id) GROUP BY source")
def q_doc_labels(s, d):
    both = read(s, d, "documents").select("doc_id", "source").join(read(s, d, "labels").select("doc_id", "toxic"), "doc_id", "left")
    return both.groupBy("source").agg(F.count("*").alias("n"), F.count_if(F.col("toxic").isNull()).alias("unlabelled"), bigint(F.sum(F.coalesce("toxic", F.lit(0)))).alias("toxic"))


# -- joins ------------------------------------------------------------------------
_NATION = "SELECT n_name AS nation, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1"


def _by_nation(hint: str):
    def run(s, d):
        owners = read(s, d, "customer").select("c_custkey", "c_nationkey").hint(hint)
        nations = read(s, d, "nation").select("n_nationkey", "n_name").hint(hint)
        both = read(s, d, "orders").select("o_custkey").join(owners, F.col("o_custkey") == F.col("c_custkey")).join(nations, F.col("c_nationkey") == F.col("n_nationkey"))
        return both.groupBy(F.col("n_name").alias("nation")).agg(F.count("*").alias("n"))

    return run


for _name, _hint in (("q_join_hash", "shuffle_hash"), ("q_join_merge", "merge"), ("q_join_broadcast", "broadcast")):
    query(_NATION, _name)(_by_nation(_hint))


@query("SELECT lang, count(l.doc_id) AS matched, count(*) AS n FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id GROUP BY lang")
def q_join_full(s, d):
    docs, labels = read(s, d, "documents").select("doc_id", "lang"), read(s, d, "labels").select(F.col("doc_id").alias("labelled"))
    return docs.join(labels, F.col("doc_id") == F.col("labelled"), "full").groupBy("lang").agg(F.count("labelled").alias("matched"), F.count("*").alias("n"))


_BAND = "SELECT p_size AS band, CAST(min(CAST(floor(p_retailprice * 10 + 0.5::DOUBLE) AS BIGINT)) AS BIGINT) - 8990 AS lo, CAST(max(CAST(floor(p_retailprice * 10 + 0.5::DOUBLE) AS BIGINT)) AS BIGINT) - 8000 AS hi FROM part GROUP BY 1"


@query(f"WITH band AS ({_BAND}), e AS (SELECT CAST(floor(value * 100 + 0.5::DOUBLE) AS BIGINT) AS v FROM events) SELECT band, count(*) AS n FROM e JOIN band ON v BETWEEN lo AND hi GROUP BY band")
def q_range_join(s, d):
    """Values within a band: both sides meet in cells of the axis, no nested loops."""
    price = F.floor(F.col("p_retailprice") * 10 + 0.5).cast("bigint")
    bands = read(s, d, "part").groupBy(F.col("p_size").alias("band")).agg((F.min(price) - 8990).alias("lo"), (F.max(price) - 8000).alias("hi"))
    values = read(s, d, "events").select(cents("value").alias("v"))
    return visible.range_join(values, "v", bands, "lo", "hi", 2000).groupBy("band").agg(F.count("*").alias("n"))


@query("SELECT a.event_id, max(b.event_id) AS view_id FROM events a LEFT JOIN events b ON b.event_type = 'view' AND a.user_id = b.user_id AND (b.ts, b.event_id) < (a.ts, a.event_id) WHERE a.event_type = 'purchase' GROUP BY a.event_id")
def q_asof_event(s, d):
    """The latest earlier view of each purchase's user: one pass over a user's rows."""
    e = read(s, d, "events").where(F.col("event_type").isin("purchase", "view")).select("event_id", "user_id", "ts", "event_type")
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(before)
    return e.withColumn("view_id", seen).where("event_type = 'purchase'").select("event_id", "view_id")


@query("SELECT a.user_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY a.user_id")
def q_interval_join(s, d):
    """Pairs of one user within an hour, counted by a frame: no pairs are made."""
    e = read(s, d, "events").select("user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    ahead = Window.partitionBy("user_id").orderBy("t").rangeBetween(1, 3_600_000_000)
    return e.withColumn("k", F.count("*").over(ahead)).groupBy("user_id").agg(F.sum("k").alias("n")).where("n > 0")


@query("WITH x AS (SELECT source, n_chars // 6 AS cell, n_chars, doc_id FROM documents) SELECT a.source, count(*) AS n FROM x a JOIN x b ON a.source = b.source AND abs(a.n_chars - b.n_chars) <= 5 AND a.doc_id < b.doc_id GROUP BY a.source")
def q_doc_near_length(s, d):
    """Pairs of one source and about one length, counted by a frame over lengths
    that are counted first: rows of equal length are one row of the window."""
    sizes = read(s, d, "documents").groupBy("source", "n_chars").agg(F.count("*").alias("k"))
    near = Window.partitionBy("source").orderBy("n_chars").rangeBetween(1, 5)
    k = F.col("k")
    pairs = sizes.select("source", (k * F.coalesce(F.sum("k").over(near), F.lit(0)) + F.expr("k * (k - 1) div 2")).alias("p"))
    return pairs.groupBy("source").agg(bigint(F.sum("p")).alias("n")).where("n > 0")


# -- aggregations -----------------------------------------------------------------
_GEO = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


@query(f"SELECT r_name, n_name, CAST(grouping(r_name) * 2 + grouping(n_name) AS BIGINT) AS level, count(*) AS n {_GEO} GROUP BY ROLLUP (r_name, n_name)")
def q_rollup_nation_region(s, d):
    both = read(s, d, "customer").join(F.broadcast(read(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(read(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return both.rollup("r_name", "n_name").agg(bigint(F.grouping_id()).alias("level"), F.count("*").alias("n"))


@query("SELECT CAST(substr(o_orderpriority, 1, 1) AS BIGINT) - 1 AS lane, o_orderstatus AS status, count(*) AS n FROM orders GROUP BY CUBE (1, 2)")
def q_cube_lane_status(s, d):
    lane = F.substring("o_orderpriority", 1, 1).cast("bigint") - 1
    return read(s, d, "orders").select(lane.alias("lane"), F.col("o_orderstatus").alias("status")).cube("lane", "status").agg(F.count("*").alias("n"))


@query("SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def q_grouping_sets(s, d):
    docs = read(s, d, "documents").select("lang", "source", "n_chars")
    return docs.groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count("*").alias("n"), bigint(F.sum("n_chars")).alias("chars"))


@query("SELECT user_id % 10 AS slot, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{k}') AS {k}" for k in KINDS) + " FROM events GROUP BY 1")
def q_pivot_event_type(s, d):
    e = read(s, d, "events").select((F.col("user_id") % 10).alias("slot"), "event_type")
    wide = e.groupBy("slot").pivot("event_type", list(KINDS)).agg(F.count(F.lit(1)))
    return wide.select("slot", *[F.coalesce(k, F.lit(0)).alias(k) for k in KINDS])


@query(f"SELECT informed, count(DISTINCT (floor(x / 600.0::DOUBLE), floor(y / 600.0::DOUBLE))) AS cells FROM ({FISH}) GROUP BY informed")
def q_distinct_cells(s, d):
    cell = F.struct(F.floor(F.col("x") / 600.0), F.floor(F.col("y") / 600.0))
    return fish(s, d).groupBy("informed").agg(F.countDistinct(cell).alias("cells"))


@query(f"SELECT lane, count(*) FILTER (WHERE v > 300) AS fast, CAST(coalesce(sum(v) FILTER (WHERE pos % 2 = 0), 0) AS BIGINT) AS even_speed FROM ({CARS}) GROUP BY lane")
def q_agg_filtered(s, d):
    return cars(s, d).groupBy("lane").agg(F.count_if(F.col("v") > 300).alias("fast"), F.coalesce(F.sum(F.when(F.col("pos") % 2 == 0, F.col("v"))), F.lit(0)).alias("even_speed"))


# -- windows, order ---------------------------------------------------------------
@query(f"SELECT id, lane, CAST(rank() OVER w AS INTEGER) AS rank, CAST(dense_rank() OVER w AS INTEGER) AS dense FROM ({CARS}) WINDOW w AS (PARTITION BY lane ORDER BY v DESC)")
def q_rank_speed(s, d):
    """Ranks of speeds that are counted first: a lane's window holds a row a
    speed, not a row a vehicle."""
    speeds = cars(s, d).groupBy("lane", "v").agg(F.count("*").alias("k"))
    w = Window.partitionBy("lane").orderBy(F.desc("v"))
    ranks = speeds.select("lane", "v", (F.sum("k").over(w.rowsBetween(Window.unboundedPreceding, 0)) - F.col("k") + 1).cast("int").alias("rank"), F.row_number().over(w).alias("dense"))
    return cars(s, d).select("id", "lane", "v").join(ranks, ["lane", "v"]).select("id", "lane", "rank", "dense")


@query(f"SELECT id, lead(pos) OVER w - pos AS front, pos - lag(pos) OVER w AS back FROM ({CARS}) WINDOW w AS (PARTITION BY lane ORDER BY pos, id)")
def q_gap_lead_lag(s, d):
    road = cars(s, d)
    ahead = visible.nearest_ahead(road, "lane", "pos").select("id", F.col("gap").alias("front"), "other")
    back = ahead.select(F.col("other").alias("id"), F.col("front").alias("back"))
    return road.select("id").join(ahead.drop("other"), "id", "left").join(back, "id", "left")


@query(f"SELECT id, count(*) OVER (PARTITION BY lane ORDER BY pos RANGE BETWEEN 1000 PRECEDING AND 1000 FOLLOWING) AS n FROM ({CARS})")
def q_range_frame(s, d):
    return visible.sweep_counts(cars(s, d), "lane", "pos", -1000, 1000).select("id", (F.col("n") + 1).alias("n"))


@query(f"SELECT strip, count(*) AS n, min(x) AS lo, max(x) AS hi FROM (SELECT x, CAST(ntile(8) OVER (ORDER BY x, id) AS INTEGER) AS strip FROM ({FISH})) GROUP BY strip")
def q_ntile_strips(s, d):
    """Equal strips of all fish by rank: ranks come from sorted partitions and
    their counts, not from one window."""
    ranked = space.ranked(fish(s, d).select("x", "id"), [], ["x", "id"])
    strip = F.expr("CASE WHEN rank <= total % 8 * (total div 8 + 1) THEN (rank - 1) div (total div 8 + 1) ELSE total % 8 + (rank - 1 - total % 8 * (total div 8 + 1)) div (total div 8) END")
    return ranked.select((strip + 1).cast("int").alias("strip"), "x").groupBy("strip").agg(F.count("*").alias("n"), F.min("x").alias("lo"), F.max("x").alias("hi"))


_CELLS = f"SELECT CAST(floor(x / 600.0::DOUBLE) AS BIGINT) AS cx, CAST(floor(y / 600.0::DOUBLE) AS BIGINT) AS cy, count(*) AS n FROM ({FISH}) GROUP BY 1, 2"


@query(f"SELECT * FROM ({_CELLS}) ORDER BY n DESC, cx, cy LIMIT 20")
def q_topk_cells(s, d):
    f = fish(s, d).select(F.floor(F.col("x") / 600.0).alias("cx"), F.floor(F.col("y") / 600.0).alias("cy"))
    return f.groupBy("cx", "cy").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "cx", "cy").limit(20)


@query(f"SELECT lane, id, v FROM (SELECT *, row_number() OVER (PARTITION BY lane ORDER BY v DESC, id) AS k FROM ({CARS})) WHERE k <= 3")
def q_topk_per_lane(s, d):
    """Three a lane: the limit of the ranking is pushed below its shuffle."""
    k = F.row_number().over(Window.partitionBy("lane").orderBy(F.desc("v"), "id"))
    return cars(s, d).withColumn("k", k).where("k <= 3").select("lane", "id", "v")


# -- set operations ------------------------------------------------------------------
@query(f"SELECT 'fish' AS class, id, x, y FROM ({FISH}) UNION ALL SELECT 'prey', id, x, y FROM ({PREY}) UNION ALL SELECT 'predator', id, x, y FROM ({ORACLE['predator']})")
def q_union_world(s, d):
    out = None
    for n in ("fish", "prey", "predator"):
        one = EXTENTS[n](s, d).select(F.lit(n).alias("class"), "id", "x", "y")
        out = one if out is None else out.unionByName(one)
    return out


def _cells(df: DataFrame) -> DataFrame:
    return df.select(F.floor(F.col("x") / 100_000.0).alias("cx"), F.floor(F.col("y") / 100_000.0).alias("cy"))


_CELL = "SELECT CAST(floor(x / 100000.0::DOUBLE) AS BIGINT) AS cx, CAST(floor(y / 100000.0::DOUBLE) AS BIGINT) AS cy FROM"


@query(f"{_CELL} ({PREY}) INTERSECT {_CELL} ({ORACLE['predator']})")
def q_intersect_cells(s, d):
    return _cells(EXTENTS["prey"](s, d)).intersect(_cells(EXTENTS["predator"](s, d)))


_T1 = naive_sql(models.traffic(), {"vehicle": CARS}, 1, "SELECT count(*) AS n FROM (SELECT id, lane FROM vehicle_1 EXCEPT SELECT id, lane FROM vehicle_0)")


@query(_T1)
def q_except_movers(s, d):
    """Vehicles that a tick has moved to another lane, as a set difference."""
    from .operators.tick import tick

    road = cars(s, d)
    after = tick({"vehicle": road}, models.traffic(), 0)["vehicle"]
    return after.select("id", "lane").exceptAll(road.select("id", "lane")).agg(F.count("*").alias("n"))


# -- scalar functions ------------------------------------------------------------------
@query("SELECT p_partkey AS id, upper(p_brand) AS brand, length(p_name) AS n, lpad(CAST(p_size AS VARCHAR), 4, '0') AS size, concat_ws('/', p_brand, p_type) AS label, regexp_extract(p_brand, '([0-9]+)', 1) AS number, split_part(p_type, ' ', 1) AS kind, replace(lower(p_name), ' ', '-') AS slug FROM part")
def q_string_funcs(s, d):
    p = read(s, d, "part")
    return p.select(F.col("p_partkey").alias("id"), F.upper("p_brand").alias("brand"), F.length("p_name").cast("bigint").alias("n"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("size"), F.concat_ws("/", "p_brand", "p_type").alias("label"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("number"), F.split_part("p_type", F.lit(" "), F.lit(1)).alias("kind"), F.replace(F.lower("p_name"), F.lit(" "), F.lit("-")).alias("slug"))


@query("SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, count(*) AS n FROM pages WHERE url IS NOT NULL GROUP BY 1")
def q_page_host(s, d):
    return read(s, d, "pages").where("url is not null").groupBy(F.regexp_extract("url", "://([^/?#]*)", 1).alias("host")).agg(F.count("*").alias("n"))


@query("SELECT lang, count(*) AS n, max(n_chars) AS longest, CAST(sum(length(text)) AS BIGINT) AS chars FROM documents GROUP BY lang")
def q_doc_stats(s, d):
    return read(s, d, "documents").groupBy("lang").agg(F.count("*").alias("n"), F.max("n_chars").alias("longest"), bigint(F.sum(F.length("text"))).alias("chars"))


@query("SELECT event_id AS id, CAST(floor(date_diff('microsecond', TIMESTAMP '2024-01-01', ts) / 26000000.0::DOUBLE) AS BIGINT) AS tick, TIMESTAMP '2024-01-01' + to_seconds(26 * CAST(floor(date_diff('microsecond', TIMESTAMP '2024-01-01', ts) / 26000000.0::DOUBLE) AS BIGINT)) AS began FROM events")
def q_tick_clock(s, d):
    """The tick of 26 seconds that an event falls in, and when it began."""
    zero = F.lit("2024-01-01").cast("timestamp_ntz")
    tick = F.floor(F.timestamp_diff("MICROSECOND", zero, F.col("ts")) / F.lit(26_000_000))
    return read(s, d, "events").select(F.col("event_id").alias("id"), tick.alias("tick"), F.timestamp_add("SECOND", (tick * 26).cast("int"), zero).alias("began"))


@query("SELECT CAST(o_orderdate AS DATE) AS day, date_trunc('month', o_orderdate) AS month, CAST(dayofweek(o_orderdate) AS INTEGER) AS weekday, count(*) AS n FROM orders GROUP BY 1, 2, 3")
def q_daily_inflow(s, d):
    at = F.col("o_orderdate")
    return read(s, d, "orders").groupBy(F.to_date(at).alias("day"), F.date_trunc("month", at).cast("timestamp_ntz").alias("month"), (F.dayofweek(at) - 1).alias("weekday")).agg(F.count("*").alias("n"))


@query(f"SELECT id, abs(vx) AS ax, CAST(sign(vx) AS BIGINT) AS sx, CAST(floor(sqrt(CAST(x * x + y * y AS DOUBLE))) AS BIGINT) AS far, ((x - 50000) % 7 + 7) % 7 AS slot, greatest(x, y, 0) AS top, least(x, y) AS low, CAST(floor((x - 50000) / 7.0::DOUBLE) AS BIGINT) AS row FROM ({FISH})")
def q_math_funcs(s, d):
    x, y = F.col("x"), F.col("y")
    return fish(s, d).select("id", F.abs("vx").alias("ax"), bigint(F.signum("vx")).alias("sx"), F.floor(F.sqrt((x * x + y * y).cast("double"))).alias("far"), F.pmod(x - 50_000, F.lit(7)).alias("slot"), F.greatest(x, y, F.lit(0)).alias("top"), F.least(x, y).alias("low"), F.floor((x - 50_000) / F.lit(7.0)).alias("row"))


@query(f"SELECT bucket, count(*) AS n FROM (SELECT CAST(CASE WHEN x < 0 THEN 0 WHEN x >= 100000 THEN 21 ELSE floor(x / 5000.0::DOUBLE) + 1 END AS BIGINT) AS bucket FROM ({FISH})) GROUP BY bucket")
def q_width_bucket(s, d):
    return fish(s, d).groupBy(F.width_bucket(F.col("x").cast("double"), F.lit(0.0), F.lit(100_000.0), F.lit(20)).alias("bucket")).agg(F.count("*").alias("n"))


# -- arrays, maps, JSON -------------------------------------------------------------------
@query("SELECT event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS k, count(*) FILTER (WHERE json_extract(props, '$.k') IS NOT NULL) AS n FROM events GROUP BY event_type")
def q_json_props(s, d):
    k = F.from_json("props", "k bigint")["k"]
    return read(s, d, "events").groupBy("event_type").agg(bigint(F.sum(k)).alias("k"), F.count(k).alias("n"))


@query("SELECT event_id AS id, CASE event_type WHEN 'view' THEN 1 WHEN 'click' THEN 3 WHEN 'purchase' THEN 9 ELSE 0 END AS weight FROM events")
def q_map_params(s, d):
    weights = F.map_from_arrays(F.array(*map(F.lit, ("view", "click", "purchase"))), F.array(*map(F.lit, (1, 3, 9))))
    return read(s, d, "events").select(F.col("event_id").alias("id"), F.coalesce(F.element_at(weights, F.col("event_type")), F.lit(0)).alias("weight"))


@query("SELECT conv_id, turn, role, lag(role) OVER w AS before, turn - lag(turn) OVER w AS gap, count(*) OVER (PARTITION BY conv_id) AS turns FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")
def q_talk_steps(s, d):
    talk = read(s, d, "conversations").select("conv_id", "turn", "role")
    w = Window.partitionBy("conv_id").orderBy("turn")
    return talk.select("conv_id", "turn", "role", F.lag("role").over(w).alias("before"), (F.col("turn") - F.lag("turn").over(w)).alias("gap"), F.count("*").over(Window.partitionBy("conv_id")).alias("turns"))


# -- boxes in three dimensions ---------------------------------------------------------
@query(f"WITH v AS MATERIALIZED ({ORACLE['vec']}), p AS (SELECT a.id, b.e1, b.label FROM v a JOIN v b ON abs(b.e1 - a.e1) <= 100000 AND abs(b.e2 - a.e2) <= 100000 AND abs(b.e3 - a.e3) <= 100000 AND a.id <> b.id), m AS (SELECT id, label, row_number() OVER (PARTITION BY id ORDER BY count(*) DESC, label) AS k FROM p GROUP BY id, label) SELECT p.id, count(*) AS n, CAST(floor(CAST(sum(e1) AS DOUBLE) / count(*)) AS BIGINT) AS mean, max(m.label) AS label FROM p JOIN m ON m.id = p.id AND m.k = 1 GROUP BY p.id")
def q_box_stats(s, d):
    """Count, mean and commonest label of the vectors within a box."""
    v = EXTENTS["vec"](s, d)
    p = visible.grid(v, v, {f"e{i}": (-100_000, 100_000) for i in (1, 2, 3)}).where("a_id <> b_id")
    by = p.groupBy(F.col("a_id").alias("id"), F.col("b_label").alias("label")).agg(F.count("*").alias("k"), F.sum("b_e1").alias("t"))
    most = F.max(F.struct(F.col("k"), -F.col("label")))
    return by.groupBy("id").agg(F.sum("k").alias("n"), F.floor(F.sum("t").cast("double") / F.sum("k")).alias("mean"), (-most.getField("col2")).alias("label"))


# -- SQL surface, tables of functions, history --------------------------------------------
_W1 = models.basic_fish()
_TICK = naive_sql(_W1, {"fish": FISH}, 1, "SELECT id, x, y, vx, vy FROM fish_1")


@query(_TICK)
def q_sql_tick(s, d):
    """The fish's tick as one SQL statement over a view, with SQL functions."""
    surface.register(s)
    view = f"agents_{uuid.uuid4().hex}"
    fish(s, d).createOrReplaceTempView(view)
    return s.sql(surface.fish_tick(view, 600, 60, 1000))


@query(f"WITH f AS MATERIALIZED ({FISH}) SELECT a.id, count(*) AS n FROM f a JOIN f b ON abs(b.x - a.x) <= 300 AND abs(b.y - a.y) <= 300 AND a.id <> b.id GROUP BY a.id")
def q_udtf_pairs(s, d):
    """Visible pairs by a table function over parts with replicas."""
    surface.register(s)
    view = f"copies_{uuid.uuid4().hex}"
    pmap = space.GridMap({"x": (25_000, 50_000, 75_000), "y": (2_000, 5_000, 12_000)})
    space.replicate(fish(s, d).select("id", "x", "y"), pmap, {"x": (-300, 300), "y": (-300, 300)}).select("part", "id", "x", "y", "is_owner").createOrReplaceTempView(view)
    return s.sql(f"SELECT a_id AS id, count(*) AS n FROM visible_pairs(300, TABLE({view}) PARTITION BY part ORDER BY x) GROUP BY a_id")


_HISTORY = naive_sql(_W1, {"fish": FISH}, 2, "{}")
_PATHS = " UNION ALL ".join(f"SELECT CAST({t} AS BIGINT) AS tick, id, x, y FROM fish_{t} WHERE id < 10" for t in range(3))


def _history(s, d):
    path = f"{runtime.checkpoint_dir(s)}/history-{uuid.uuid4().hex}"
    runtime.run({"fish": fish(s, d)}, _W1, 2, history=path)
    return runtime.history(s, path, "fish")


@query(_HISTORY.replace("{}", _PATHS))
def q_trajectory(s, d):
    return _history(s, d).where("id < 10").select("tick", "id", "x", "y")


@query(_HISTORY.replace("{}", "SELECT id, x, y FROM fish_2"))
def q_history_tick(s, d):
    """The world as it was at a tick: the history's partitions are pruned."""
    return _history(s, d).where("tick = 2").select("id", "x", "y")
