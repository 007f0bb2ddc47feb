"""The relational and streaming surface that the repair methods stand on."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .model import Plan, Repair, cmp, eq
from .relops.asof import asof_join, band_join, events_within
from .session import shared_dir, written
from .sources.tables import ReadingsSource, load, load_plan, read, save_plan, write
from .streaming import streams

QUERIES, ORACLES = {}, {}


def query(sql: str | None = None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql is not None:
            ORACLES[fn.__name__] = sql.strip()
        return fn

    return add


def _scratch(spark, name: str) -> str:
    import uuid

    return f"{shared_dir(spark)}/repairflow/{name}-{uuid.uuid4().hex}"


# Sources and sinks.


def _round_trip(spark, sf, fmt: str, **options) -> DataFrame:
    path = _scratch(spark, fmt)
    nation = load(spark, sf, "nation").select("n_nationkey", "n_name", "n_regionkey")
    write(nation, path, fmt, **options)
    return read(spark, path, fmt, "n_nationkey int, n_name string, n_regionkey int", **options)


NATION = "select n_nationkey, n_name, n_regionkey from nation"


@query(NATION)
def rel_csv(spark, sf):
    return _round_trip(spark, sf, "csv", header="true")


@query(NATION)
def rel_json(spark, sf):
    return _round_trip(spark, sf, "json")


@query(NATION)
def rel_orc(spark, sf):
    return _round_trip(spark, sf, "orc")


@query("select r_name as value from region")
def rel_text(spark, sf):
    path = _scratch(spark, "text")
    write(load(spark, sf, "region").select(F.col("r_name").alias("value")), path, "text")
    return read(spark, path, "text")


@query("select l_returnflag, cast(count(*) as bigint) as n from lineitem where l_returnflag = 'R' group by 1")
def rel_partitioned_sink(spark, sf):
    path = _scratch(spark, "parts")
    write(load(spark, sf, "lineitem").select("l_orderkey", "l_returnflag"), path, partition_by=("l_returnflag",))
    return spark.read.parquet(path).filter("l_returnflag = 'R'").groupBy("l_returnflag").agg(F.count("*").alias("n"))


@query("select event_id as rec_id, case when event_id % 100 = 7 then value * 20.0::double else value end as reading, 50.0 + ((event_id * 37) % 19) / 4.0 as truth from events")
def rel_data_source(spark, sf):
    """The values of all events under the noise of a source, joined by their ids."""
    spark.dataSource.register(ReadingsSource.make())
    events = load(spark, sf, "events").select(F.col("event_id").alias("rec_id"), "value")
    rows = (events.agg(F.max("rec_id")).first()[0] or 0) + 1
    noise = spark.read.format("noisy_readings").options(rows=rows, parts=max(4, rows // 250_000)).load()
    return events.join(noise, "rec_id").select("rec_id", (F.col("value") * (F.col("reading") / F.col("truth"))).alias("reading"), "truth")


@query("select p_partkey, case when p_name = 'old ring' then 'cold ring' when p_retailprice < 905 then 'cheap' else p_name end as p_name from part")
def rel_plan_file(spark, sf):
    """A plan saved, loaded and applied to another relation of its attributes."""
    path = _scratch(spark, "plan")
    # One bundle: both read the name as it was, and the later one overwrites the earlier.
    both = [Repair((cmp("p_retailprice", "lt", 905.0),), "p_name", "cheap", bundle="name"), Repair((eq("p_name", "old ring"),), "p_name", "cold ring", bundle="name")]
    save_plan(spark, Plan(both), path)
    from .plans.apply import apply_plan

    return apply_plan(load(spark, sf, "part"), load_plan(spark, path)).select("p_partkey", "p_name")


# Joins.


@query("select n_name, cast(count(*) as bigint) as n from customer join nation on c_nationkey = n_nationkey group by 1")
def rel_join_broadcast(spark, sf):
    nation = load(spark, sf, "nation")
    return load(spark, sf, "customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query("select c_mktsegment, cast(count(o_orderkey) as bigint) as n from customer left join orders on c_custkey = o_custkey group by 1")
def rel_join_left(spark, sf):
    orders = load(spark, sf, "orders").select("o_orderkey", "o_custkey").hint("merge")
    return load(spark, sf, "customer").join(orders, F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_mktsegment").agg(F.count("o_orderkey").alias("n"))


@query("select cast(count(*) as bigint) as n, cast(count(l.p_partkey) as bigint) as l, cast(count(r.p_partkey) as bigint) as r from (select * from part where p_size < 20) l full join (select * from part where p_size > 10) r on l.p_partkey = r.p_partkey")
def rel_join_full(spark, sf):
    part = load(spark, sf, "part").select("p_partkey", "p_size")
    a, b = part.filter("p_size < 20").select(F.col("p_partkey").alias("x")), part.filter("p_size > 10").select(F.col("p_partkey").alias("y"))
    return a.join(b, F.col("x") == F.col("y"), "full").agg(F.count("*").alias("n"), F.count("x").alias("l"), F.count("y").alias("r"))


@query("select cast(count(*) as bigint) as n from customer where c_custkey in (select o_custkey from orders)")
def rel_semi(spark, sf):
    return load(spark, sf, "customer").join(load(spark, sf, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").agg(F.count("*").alias("n"))


@query("select cast(count(*) as bigint) as n from customer where c_custkey not in (select o_custkey from orders)")
def rel_anti(spark, sf):
    return load(spark, sf, "customer").join(load(spark, sf, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").agg(F.count("*").alias("n"))


@query("select event_id, (select e2.value from events e2 where e2.event_type = e.event_type and e2.ts <= e.ts and e2.event_id % 10 = 0 order by e2.ts desc limit 1) as value from events e where event_id % 10 = 5")
def rel_asof(spark, sf):
    e = load(spark, sf, "events").select("event_id", "event_type", "ts", "value")
    left, right = e.filter("event_id % 10 = 5").drop("value"), e.filter("event_id % 10 = 0")
    return asof_join(left, right, ["event_type"], "ts", "ts", "value").select("event_id", "value")


@query("select cast(count(*) as bigint) as n from supplier a join supplier b on abs(a.s_acctbal - b.s_acctbal) <= 25.0")
def rel_band(spark, sf):
    s = load(spark, sf, "supplier")
    return band_join(s.select(F.col("s_acctbal").alias("a")), s.select(F.col("s_acctbal").alias("b")), "a", "b", 25.0).agg(F.count("*").alias("n"))


@query("select a.event_id, cast(count(b.event_id) as bigint) as n from (select * from events where event_id % 50 = 0) a join events b on a.event_type = b.event_type and b.ts <= a.ts and b.ts >= a.ts - interval '5 hours' group by 1")
def rel_interval(spark, sf):
    e = load(spark, sf, "events").select("event_id", "event_type", "ts")
    pairs = events_within(e.filter("event_id % 50 = 0").withColumnRenamed("ts", "pts"), e.select(F.col("event_id").alias("other"), "event_type", F.col("ts").alias("ets")), "event_type", "pts", "ets", 5 * 3600)
    return pairs.groupBy("event_id").agg(F.count("*").alias("n"))


# The two above follow their SQL, which takes parts of the events; these take all of them.


@query()
def rel_asof_all(spark, sf):
    """Each event with the value of the last one of its type before its time (of several
    at one time, the greatest id)."""
    e = load(spark, sf, "events").select("event_id", "event_type", "ts", "value")
    right = e.groupBy("event_type", "ts").agg(F.max_by("value", "event_id").alias("value"))
    return asof_join(e.drop("value"), right, ["event_type"], "ts", "ts", "value", strict=True).select("event_id", "value")


@query()
def rel_interval_all(spark, sf):
    """For each event the number of its type in the five hours up to it."""
    e = load(spark, sf, "events").select("event_id", "event_type", "ts")
    pairs = events_within(e.withColumnRenamed("ts", "pts"), e.select(F.col("event_id").alias("other"), "event_type", F.col("ts").alias("ets")), "event_type", "pts", "ets", 5 * 3600)
    return pairs.groupBy("event_id").agg(F.count("*").alias("n"))


@query("select r_name, p as setting from region cross join (values (1), (2), (3)) t(p)")
def rel_cross(spark, sf):
    return load(spark, sf, "region").select("r_name").crossJoin(F.broadcast(spark.range(1, 4).select(F.col("id").cast("int").alias("setting"))))


# Aggregates, grouping sets, windows, sets.


@query("select l_returnflag, cast(count(*) as bigint) as n, round(sum(l_quantity), 4) as s, round(avg(l_discount), 6) as a, round(stddev_samp(l_quantity), 6) as d, round(corr(l_quantity, l_extendedprice), 6) as c, round(regr_slope(l_extendedprice, l_quantity), 4) as b, cast(count(distinct l_partkey) as bigint) as k, cast(count(*) filter (where l_tax > 0.04) as bigint) as f from lineitem group by 1")
def rel_aggregates(spark, sf):
    return load(spark, sf, "lineitem").groupBy("l_returnflag").agg(
        F.count("*").alias("n"), F.round(F.sum("l_quantity"), 4).alias("s"), F.round(F.avg("l_discount"), 6).alias("a"), F.round(F.stddev_samp("l_quantity"), 6).alias("d"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("c"),
        F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("b"), F.count_distinct("l_partkey").alias("k"), F.count_if(F.col("l_tax") > 0.04).alias("f"),
    )


@query("select l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus) as g, cast(count(*) as bigint) as n from lineitem group by cube (l_returnflag, l_linestatus)")
def rel_cube(spark, sf):
    return load(spark, sf, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("g"), F.count("*").alias("n"))


@query("select l_returnflag, l_linestatus, cast(count(*) as bigint) as n from lineitem group by rollup (l_returnflag, l_linestatus)")
def rel_rollup(spark, sf):
    return load(spark, sf, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("select l_returnflag, l_linestatus, cast(count(*) as bigint) as n from lineitem group by grouping sets ((l_returnflag), (l_linestatus))")
def rel_grouping_sets(spark, sf):
    return load(spark, sf, "lineitem").groupingSets([["l_returnflag"], ["l_linestatus"]], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("select n_regionkey, cast(count(*) filter (n_nationkey % 2 = 0) as bigint) as even, cast(count(*) filter (n_nationkey % 2 = 1) as bigint) as odd from nation group by 1")
def rel_pivot(spark, sf):
    return load(spark, sf, "nation").withColumn("p", F.when(F.col("n_nationkey") % 2 == 0, "even").otherwise("odd")).groupBy("n_regionkey").pivot("p", ["even", "odd"]).agg(F.count("n_nationkey"))


@query("select n_nationkey, attr, value from (select n_nationkey, 'n_name' as attr, n_name as value from nation union all select n_nationkey, 'n_regionkey', cast(n_regionkey as varchar) from nation) t")
def rel_unpivot(spark, sf):
    return load(spark, sf, "nation").select("n_nationkey", "n_name", F.col("n_regionkey").cast("string").alias("n_regionkey")).unpivot("n_nationkey", ["n_name", "n_regionkey"], "attr", "value")


@query(
    """select event_id, row_number() over w as rn, ntile(4) over w as q, round(percent_rank() over w, 6) as pr, lag(event_id) over w as before, lead(event_id) over w as after,
    round(sum(value) over (partition by event_type order by ts, event_id rows between 4 preceding and current row), 4) as run from events window w as (partition by event_type order by ts, event_id)"""
)
def rel_windows(spark, sf):
    w = Window.partitionBy("event_type").orderBy("ts", "event_id")
    return load(spark, sf, "events").select(
        "event_id", F.row_number().over(w).alias("rn"), F.ntile(4).over(w).alias("q"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"),
        F.round(F.sum("value").over(w.rowsBetween(-4, 0)), 4).alias("run"),
    )


@query("select event_id, cast(count(*) over (partition by event_type order by ts range between interval 5 hours preceding and current row) as bigint) as n from events")
def rel_range_window(spark, sf):
    w = Window.partitionBy("event_type").orderBy("us").rangeBetween(-5 * 3600 * 1_000_000, 0)
    return load(spark, sf, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(w).alias("n"))


@query("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10")
def rel_top(spark, sf):
    return load(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("select c_mktsegment, c_custkey from (select *, row_number() over (partition by c_mktsegment order by c_acctbal desc, c_custkey) as rn from customer) t where rn <= 3")
def rel_top_per_group(spark, sf):
    w = Window.partitionBy("c_mktsegment").orderBy(F.desc("c_acctbal"), "c_custkey")
    return load(spark, sf, "customer").withColumn("rn", F.row_number().over(w)).filter("rn <= 3").select("c_mktsegment", "c_custkey")


@query("select * from ((select n_regionkey as k from nation except all select r_regionkey from region) union all (select n_regionkey from nation intersect select r_regionkey from region)) t")
def rel_set_operations(spark, sf):
    a, b = load(spark, sf, "nation").select(F.col("n_regionkey").alias("k")), load(spark, sf, "region").select(F.col("r_regionkey").alias("k"))
    return a.exceptAll(b).unionByName(a.intersect(b))


# Functions.


@query("select p_partkey, upper(p_name) as u, split_part(p_name, ' ', 1) as a, regexp_replace(p_name, '[aeiou]', '*', 'g') as v, levenshtein(p_name, 'old ring') as d, md5(p_name) as h, length(p_name) as n, translate(p_name, 'abc', 'xyz') as t from part")
def rel_strings(spark, sf):
    c = F.col("p_name")
    return load(spark, sf, "part").select("p_partkey", F.upper(c).alias("u"), F.split_part(c, F.lit(" "), F.lit(1)).alias("a"), F.regexp_replace(c, "[aeiou]", "*").alias("v"), F.levenshtein(c, F.lit("old ring")).alias("d"), F.md5(c).alias("h"), F.length(c).alias("n"), F.translate(c, "abc", "xyz").alias("t"))


@query("select o_orderkey, date_trunc('month', o_orderdate) as m, date_diff('day', date '1992-01-01', o_orderdate::date) as d, year(o_orderdate)::int as y from orders")
def rel_dates(spark, sf):
    t = F.col("o_orderdate")
    return load(spark, sf, "orders").select("o_orderkey", F.date_trunc("month", t).cast("timestamp_ntz").alias("m"), F.datediff(t, F.lit("1992-01-01").cast("date")).alias("d"), F.year(t).alias("y"))


@query("select event_id, round(ln(1 + abs(value)), 6) as l, round(sqrt(abs(value)), 6) as r, greatest(value, 50) as g, cast(floor(value / 10) as bigint) as b from events")
def rel_math(spark, sf):
    v = F.col("value")
    return load(spark, sf, "events").select("event_id", F.round(F.log1p(F.abs(v)), 6).alias("l"), F.round(F.sqrt(F.abs(v)), 6).alias("r"), F.greatest(v, F.lit(50.0)).alias("g"), F.floor(v / 10).alias("b"))


@query("select p_partkey, w, cast(length(w) as int) as n from (select p_partkey, unnest(string_split(p_name, ' ')) as w from part) t where length(w) > 3")
def rel_arrays(spark, sf):
    words = F.filter(F.split("p_name", " "), lambda w: F.length(w) > 3)
    return load(spark, sf, "part").select("p_partkey", F.explode(words).alias("w")).withColumn("n", F.length("w"))


@query("select label, round(avg(x), 5) as mean, cast(count(*) as bigint) as n from (select label, list_sum(embedding) as x from embeddings) t group by 1")
def rel_array_aggregate(spark, sf):
    total = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x)
    return load(spark, sf, "embeddings").select("label", total.alias("x")).groupBy("label").agg(F.round(F.avg("x"), 5).alias("mean"), F.count("*").alias("n"))


@query("select role, max(turn) as turns, cast(count(*) as bigint) as n from conversations group by 1")
def rel_conversations(spark, sf):
    return load(spark, sf, "conversations").groupBy("role").agg(F.max("turn").alias("turns"), F.count("*").alias("n"))


@query("select cast(count(*) as bigint) as n from pages where html like '%<article>%'")
def rel_pages_filter(spark, sf):
    return load(spark, sf, "pages").filter(F.col("html").contains("<article>")).agg(F.count("*").alias("n"))


_RECURSIVE = "with recursive sizes as (select p_size as k, count(*) as n from {} group by 1), t(i, s) as (select k, n from sizes where k = 1 union all select t.i + 1, t.s + z.n from t join sizes z on z.k = t.i + 1 where t.i < 10) select i, s from t"


@query(_RECURSIVE.format("part"))
def rel_recursive(spark, sf):
    """How many parts there are of the first sizes, size by size."""
    sizes = written(load(spark, sf, "part").select("p_size"), "sizes")
    return spark.sql(_RECURSIVE.format("{part}"), part=sizes)


@query("select c_mktsegment, cast(count(*) as bigint) as n from customer where c_acctbal > 100.0 group by 1")
def rel_sql_parameters(spark, sf):
    return spark.sql("select c_mktsegment, count(*) as n from {t} where c_acctbal > :least group by 1", args={"least": 100.0}, t=load(spark, sf, "customer"))


@query()
def rel_approximate(spark, sf):
    return load(spark, sf, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median"))


@query()
def rel_sample(spark, sf):
    return load(spark, sf, "orders").sample(0.1, seed=1).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@query("select c_mktsegment, round(avg(c_acctbal), 4) as m from customer group by 1")
def rel_grouped_function(spark, sf):
    """A user's aggregate as a pandas function over groups."""

    @F.pandas_udf("double")
    def mean(v: pd.Series) -> float:
        return float(v.mean())

    return load(spark, sf, "customer").groupBy("c_mktsegment").agg(F.round(mean("c_acctbal"), 4).alias("m"))


@query("select r_name, c from (select r_name, unnest(string_split(lower(r_name), 'a')) as c from region) t where c <> ''")
def rel_table_function(spark, sf):
    """A tool behind a table function."""

    @F.udtf(returnType="c: string")
    class Pieces:
        def eval(self, name: str):
            for part in name.lower().split("a"):
                if part:
                    yield (part,)

    spark.udtf.register("pieces", Pieces)
    load(spark, sf, "region").createOrReplaceTempView("_regions")
    return spark.sql("select r_name, c from _regions, lateral pieces(r_name)")


# Streams, run over what is there.


def _stream(spark, sf, name: str) -> DataFrame:
    """The table as a stream of files (a copy in a folder, for the file source)."""
    path = _scratch(spark, f"in-{name}")
    df = load(spark, sf, name)
    df.write.parquet(path)
    return streams.read_stream(spark, path, df.schema)


@query("select event_id, case when event_type = 'click' then 'press' else event_type end as event_type, case when value > 200 then null else value end as value from events")
def stream_clean(spark, sf):
    plan = Plan([Repair((eq("event_type", "click"),), "event_type", "press"), Repair((cmp("value", "gt", 200.0),), "value", None)])
    return streams.run_to_table(streams.clean_stream(_stream(spark, sf, "events"), plan).select("event_id", "event_type", "value"), "cleaned")


@query("select time_bucket(interval '1 day', ts, timestamp '1970-01-01') as start, event_type, cast(count(*) as bigint) as n from events group by 1, 2")
def stream_tumbling(spark, sf):
    counts = streams.monitor(_stream(spark, sf, "events"), "ts", "1 day", "1 day", None, F.count("*").alias("n"), by=("event_type",))
    return streams.run_to_table(counts, "tumbling", "complete").select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@query("select start, cast(count(*) as bigint) as n from (select time_bucket(interval '1 hour', ts, timestamp '1970-01-01') - i * interval '1 hour' as start from events, range(5) r(i)) t group by 1")
def stream_sliding(spark, sf):
    counts = streams.monitor(_stream(spark, sf, "events"), "ts", "1 day", "5 hours", "1 hour", F.count("*").alias("n"))
    return streams.run_to_table(counts, "sliding", "complete").select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")


@query("with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval '6 hours' then 0 else 1 end as new from events), s as (select user_id, sum(new) over (partition by user_id order by ts) as k from g) select user_id, cast(count(*) as bigint) as n from s group by user_id, k")
def stream_sessions(spark, sf):
    got = streams.sessions(_stream(spark, sf, "events"), "ts", "1 day", "6 hours", "user_id")
    return streams.run_to_table(got, "sessions", "complete").select("user_id", "n")


@query("select event_type, cast(count(*) as bigint) as n from events group by 1")
def stream_running_counts(spark, sf):
    return streams.run_to_table(streams.running_counts(_stream(spark, sf, "events"), "event_type"), "running", "complete")


@query("select event_id, event_type from events")
def stream_without_repeats(spark, sf):
    twice = _stream(spark, sf, "events").select("event_id", "event_type", "ts", F.explode(F.array(F.lit(1), F.lit(2))).alias("copy"))
    return streams.run_to_table(streams.without_repeats(twice, "ts", "1 day", ["event_id"]).select("event_id", "event_type"), "once")


@query("select event_id, event_type, value, last_value(case when value <= 150 then value end ignore nulls) over (partition by event_type order by ts, event_id rows between unbounded preceding and current row) as good from events")
def stream_last_good(spark, sf):
    s = streams.last_good_stream(_stream(spark, sf, "events"), "event_type", "ts", "value", lambda v: v > 150, key="event_id")
    return streams.run_to_table(s, "good")


@query("select a.event_id from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval '1 hour' where a.event_type = 'click' and b.event_type = 'purchase'")
def stream_join(spark, sf):
    e = _stream(spark, sf, "events").select("event_id", "user_id", "event_type", "ts")
    left = e.filter("event_type = 'click'").select("event_id", "user_id", "ts")
    right = _stream(spark, sf, "events").filter("event_type = 'purchase'").select(F.col("user_id").alias("user_id_r"), F.col("ts").alias("rts"))
    return streams.run_to_table(streams.join_within(left, right, "user_id", "ts", "rts", "1 day", "1 hour").select("event_id"), "joined")


@query("select cast(count(*) as bigint) as repairs from (select item from (select p_name as item from part) t group by 1) u")
def stream_pool(spark, sf):
    """Repairs appended to a folder, read as a stream, drained batch by batch."""
    from .plans.pool import equality_repairs

    values = load(spark, sf, "part").select(F.col("p_name").alias("v")).distinct()
    pool = equality_repairs(values, {"item": F.col("v")}, "item", F.upper("v"), "upper")
    path, out = _scratch(spark, "pool"), _scratch(spark, "drained")
    pool.repartition(3).write.parquet(path)
    streams.search_stream(streams.pool_stream(spark, path), lambda batch, i: batch.write.mode("append").parquet(out), _scratch(spark, "checkpoint"))
    return written(spark.read.parquet(out).agg(F.count("*").alias("repairs")), "count")
