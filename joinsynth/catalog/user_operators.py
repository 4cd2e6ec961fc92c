"""Operators around the methods (``op_*``): scans, joins, aggregates, windows, functions, UDFs, streams."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import noise
from ..operators import kernel, release
from ..operators.sensitivity import degree_table
from ..plans.elimination import join_size
from ..relation import load
from ..sources.formats import round_trip, shared_folder
from ..sources.workloads import TWO
from ..streaming import degrees as stream
from .core import _DEG, union_all
from .noise_and_release import _FAM2, _PE, ZERO, kernel_sql
from .registry import DELTA, EPS, LAM, SEED, TWO_ANSWERS, entry, ladder_sql, size_sql, two_queries, uniform_sql


def t(s: SparkSession, d: str, name: str) -> DataFrame:
    return s.read.parquet(f"{d}/{name}.parquet")


# Sources, sinks, projections, filters -------------------------------------------------------------


@entry("op_scan_pruned", "select l_linestatus, count(*)::bigint as n, sum(l_quantity::bigint)::bigint as q from lineitem where l_returnflag = 'R' group by 1")
def scan(s, d):
    return t(s, d, "lineitem").filter("l_returnflag = 'R'").groupBy("l_linestatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("q"))


@entry("op_write_read_roundtrip", "select o_custkey as K, o_orderpriority as P, count(*)::bigint as freq from orders group by all")
def write_read(s, d):
    return round_trip(load(s, d, TWO).frames[0], "parquet")


@entry("op_formats_csv_json_orc", "select unnest(['csv', 'json', 'orc']) as kind, r_regionkey, r_name from region")
def formats(s, d):
    return union_all([round_trip(t(s, d, "region"), k).select(F.lit(k).alias("kind"), "r_regionkey", "r_name") for k in ("csv", "json", "orc")])


@entry("op_partitioned_prune", "select count(*)::bigint as n, sum(user_id)::bigint as users from events where event_type = 'view'")
def partitioned(s, d):
    events = t(s, d, "events").select("event_id", "user_id", "event_type")
    return round_trip(events, "parquet", "event_type").filter("event_type = 'view'").agg(F.count("*").alias("n"), F.sum("user_id").alias("users"))


@entry("op_rename_natural", "select count(*)::bigint as n from customer join orders on c_custkey = o_custkey")
def rename(s, d):
    left = t(s, d, "customer").select(F.col("c_custkey").alias("K"))
    return left.join(t(s, d, "orders").select(F.col("o_custkey").alias("K")), "K").agg(F.count("*").alias("n"))


_BINS = {"c_acctbal": ("customer", -1000, 10000), "s_acctbal": ("supplier", -1000, 10000), "o_totalprice": ("orders", 0, 500000), "l_quantity": ("lineitem", 1, 51)}


@entry("op_discretise_bins", " union all ".join(f"select '{c}' as attribute, (case when {c} < {a} then 0 when {c} >= {b} then 6 else floor(({c} - {a}) * 5 / ({b} - {a})) + 1 end)::bigint as bin, count(*)::bigint as n from {tab} group by all" for c, (tab, a, b) in _BINS.items()))
def bins(s, d):
    return union_all([t(s, d, tab).groupBy(F.lit(c).alias("attribute"), F.width_bucket(c, F.lit(float(a)), F.lit(float(b)), F.lit(5)).alias("bin")).agg(F.count("*").alias("n")) for c, (tab, a, b) in _BINS.items()])


@entry("op_discretise_time", "select 'order_month' as attribute, month(o_orderdate)::int as part, count(*)::bigint as n from orders group by all union all select 'ship_month', month(l_shipdate)::int, count(*)::bigint from lineitem group by all union all select 'event_hour', hour(ts)::int, count(*)::bigint from events group by all")
def times(s, d):
    parts = (("order_month", "orders", F.month("o_orderdate")), ("ship_month", "lineitem", F.month("l_shipdate")), ("event_hour", "events", F.hour("ts")))
    return union_all([t(s, d, tab).groupBy(F.lit(a).alias("attribute"), c.alias("part")).agg(F.count("*").alias("n")) for a, tab, c in parts])


@entry("op_filter_predicates", "select count(*) filter (p_size between 10 and 20)::bigint as in_range, count(*) filter (p_brand in ('Brand#1', 'Brand#2'))::bigint as in_list, count(*) filter (p_name like '%a%')::bigint as like_a, count(*) filter (p_type is not distinct from null)::bigint as null_type, count(*) filter (not (p_size < 5 or p_retailprice > 1000))::bigint as combined from part")
def predicates(s, d):
    n = lambda c, name: F.count_if(F.coalesce(c, F.lit(False))).alias(name)
    return t(s, d, "part").agg(
        n(F.col("p_size").between(10, 20), "in_range"), n(F.col("p_brand").isin("Brand#1", "Brand#2"), "in_list"), n(F.col("p_name").like("%a%"), "like_a"),
        n(F.col("p_type").eqNullSafe(F.lit(None)), "null_type"), n(~((F.col("p_size") < 5) | (F.col("p_retailprice") > 1000)), "combined"),
    )


# Joins --------------------------------------------------------------------------------------------


@entry("op_join_broadcast", "select n_name, count(*)::bigint as n from customer join nation on c_nationkey = n_nationkey group by 1")
def join_broadcast(s, d):
    """The nation table is a dimension of fixed size."""
    return t(s, d, "customer").join(F.broadcast(t(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


for _kind, _hint in (("sortmerge", "merge"), ("shufflehash", "shuffle_hash")):
    entry(f"op_join_{_kind}", "select o_orderpriority, count(*)::bigint as n from orders join lineitem on o_orderkey = l_orderkey group by 1")(
        lambda s, d, h=_hint: t(s, d, "orders").hint(h).join(t(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))
    )


@entry("op_join_left_domain", "select c_custkey as K, coalesce(n, 0)::bigint as deg from customer left join (select user_id, count(*) as n from events group by 1) on user_id = c_custkey")
def join_left(s, d):
    found = t(s, d, "events").groupBy(F.col("user_id").alias("K")).agg(F.count("*").alias("n"))
    return t(s, d, "customer").select(F.col("c_custkey").alias("K")).join(found, "K", "left").select("K", F.coalesce("n", F.lit(0)).alias("deg"))


@entry("op_join_full_degrees", f"select K, deg1, deg2 from {_DEG}")
def join_full(s, d):
    return degree_table(load(s, d, TWO))


for _kind in ("semi", "anti"):
    entry(f"op_join_{_kind}", f"select c_custkey from customer where c_custkey {'not ' * (_kind == 'anti')}in (select user_id from events)")(
        lambda s, d, k=_kind: t(s, d, "customer").join(t(s, d, "events").select("user_id"), F.col("c_custkey") == F.col("user_id"), f"left_{k}").select("c_custkey")
    )


@entry("op_join_range_bucket", f"select K, {ladder_sql('greatest(deg1, deg2)', LAM)}::int as bucket from {_DEG}")
def join_range(s, d):
    """Degrees against a table of 64 bucket edges: a range condition on a broadcast side of fixed size."""
    edges = s.createDataFrame([(i, 0.0 if i == 1 else LAM * 2.0 ** (i - 1), LAM * 2.0**i) for i in range(1, 64)], "bucket int, lo double, hi double")
    deg = degree_table(load(s, d, TWO)).select("K", F.greatest("deg1", "deg2").cast("double").alias("g"))
    return deg.join(F.broadcast(edges), (F.col("g") > F.col("lo")) & (F.col("g") <= F.col("hi"))).select("K", "bucket")


@entry("op_join_asof", "select l_orderkey, l_linenumber, coalesce(max(p.o_orderkey), -1)::bigint as latest_order, count(distinct rid)::bigint as n from (select l.rid, l.l_orderkey, l.l_linenumber, o.o_custkey, max(q.o_orderdate) as at from (select *, row_number() over () as rid from lineitem) l join orders o on o.o_orderkey = l.l_orderkey left join orders q on q.o_custkey = o.o_custkey and q.o_orderdate <= l.l_shipdate group by all) x left join orders p on p.o_custkey = x.o_custkey and p.o_orderdate = x.at group by 1, 2")
def join_asof(s, d):
    """Latest order of the same customer at or before each shipment: one shuffle by customer, a window over both tables' rows."""
    orders = t(s, d, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    ships = t(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_shipdate").join(orders.select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    none = F.lit(None)
    rows = orders.select("o_custkey", F.col("o_orderdate").alias("at"), F.lit(0).alias("kind"), F.struct("o_orderdate", "o_orderkey").alias("o"), none.cast("bigint").alias("l_orderkey"), none.cast("int").alias("l_linenumber"))
    rows = rows.unionByName(ships.select("o_custkey", F.col("l_shipdate").alias("at"), F.lit(1).alias("kind"), none.cast("struct<o_orderdate: timestamp, o_orderkey: bigint>").alias("o"), "l_orderkey", "l_linenumber"))
    w = W.partitionBy("o_custkey").orderBy("at", "kind", "o.o_orderkey").rowsBetween(W.unboundedPreceding, W.currentRow)
    found = rows.withColumn("o", F.last("o", ignorenulls=True).over(w)).filter("kind = 1")
    return found.groupBy("l_orderkey", "l_linenumber").agg(F.coalesce(F.max("o.o_orderkey"), F.lit(-1)).alias("latest_order"), F.count("*").alias("n"))


@entry("op_join_interval", "select a.event_id as signup_id, count(*)::bigint as n from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour where a.event_type = 'signup' group by 1")
def join_interval(s, d):
    a = t(s, d, "events").filter("event_type = 'signup'").select(F.col("user_id").alias("u"), F.col("event_id").alias("signup_id"), F.col("ts").alias("a_ts"))
    b = t(s, d, "events").select("user_id", "ts")
    return a.join(b, F.expr("u = user_id and ts >= a_ts and ts <= a_ts + interval 1 hour")).groupBy("signup_id").agg(F.count("*").alias("n"))


@entry("op_cross_domain", "select S, P, E, (select count(*) from customer)::bigint as volume from (select distinct c_mktsegment as S from customer), (select distinct o_orderpriority as P from orders), (select distinct event_type as E from events)")
def cross(s, d):
    one = lambda tab, c, a: t(s, d, tab).select(F.col(c).alias(a)).distinct()
    keys = t(s, d, "customer").agg(F.count("*").alias("volume"))
    return one("customer", "c_mktsegment", "S").crossJoin(one("orders", "o_orderpriority", "P")).crossJoin(one("events", "event_type", "E")).crossJoin(keys)


# Aggregates ---------------------------------------------------------------------------------------


@entry("op_agg_basic", "select o_orderpriority, count(*)::bigint as n, round(sum(o_totalprice), 2) as total, round(avg(o_totalprice), 4) as mean, min(o_totalprice) as least, max(o_totalprice) as most from orders group by 1")
def agg_basic(s, d):
    p = F.col("o_totalprice").cast("decimal(18,2)")
    return t(s, d, "orders").groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum(p).cast("double"), 2).alias("total"), F.round((F.sum(p).cast("double") / F.count("*")), 4).alias("mean"), F.min("o_totalprice").alias("least"), F.max("o_totalprice").alias("most"))


@entry("op_agg_distinct", "select o_orderpriority, count(distinct o_custkey)::bigint as customers from orders group by 1")
def agg_distinct(s, d):
    return t(s, d, "orders").groupBy("o_orderpriority").agg(F.count_distinct("o_custkey").alias("customers"))


@entry("op_agg_conditional", "select l_returnflag, count(*) filter (l_linestatus = 'F')::bigint as f, sum(case when l_quantity > 25 then 1 else 0 end)::bigint as large from lineitem group by 1")
def agg_conditional(s, d):
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_if(F.col("l_linestatus") == "F").alias("f"), F.sum(F.when(F.col("l_quantity") > 25, 1).otherwise(0)).alias("large"))


@entry("op_agg_approx_distinct")
def agg_approx(s, d):
    return t(s, d, "orders").agg(F.approx_count_distinct("o_custkey", 0.02).alias("approx"), F.count_distinct("o_custkey").alias("exact"))


@entry("op_agg_percentile", f"select quantile_cont(deg1, 0.5)::double as d1, quantile_cont(deg2, 0.9)::double as d2 from {_DEG}")
def agg_percentile(s, d):
    return degree_table(load(s, d, TWO)).agg(F.percentile("deg1", 0.5).alias("d1"), F.percentile("deg2", 0.9).alias("d2"))


@entry("op_agg_maxby", f"select bucket, arg_max(K, deg1 * deg2 * 1000000 - K)::bigint as heaviest from (select *, {ladder_sql('greatest(deg1, deg2)', LAM)} as bucket from {_DEG}) group by bucket")
def agg_maxby(s, d):
    from ..operators.partition import bucket_of

    deg = degree_table(load(s, d, TWO)).withColumn("bucket", bucket_of(F.greatest("deg1", "deg2"), LAM))
    return deg.groupBy("bucket").agg(F.max_by("K", F.struct(F.col("deg1") * F.col("deg2"), F.negative("K"))).alias("heaviest"))


def _marginals(s, d, sets):
    base = join_size(load(s, d, TWO), ("P", "E")).select("P", "E", "val")
    base.createOrReplaceTempView("joinsynth_marginals")
    return s.sql(f"select P, E, cast(sum(val) as bigint) as n from joinsynth_marginals group by {sets}")


for _name, _sets in (("cube", "cube (P, E)"), ("rollup", "rollup (P, E)"), ("grouping_sets", "grouping sets ((P), (E), ())")):
    entry(f"op_{_name}", f"select P, E, count(*)::bigint as n from (select o_orderpriority as P, event_type as E from orders join events on o_custkey = user_id) group by {_sets}")(
        lambda s, d, g=_sets: _marginals(s, d, g)
    )


# Windows, order, sets -----------------------------------------------------------------------------


@entry("op_win_rank", "select c_nationkey, c_custkey, rank() over (partition by c_nationkey order by c_acctbal desc)::int as r from customer qualify r <= 3")
def win_rank(s, d):
    w = W.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"))
    return t(s, d, "customer").withColumn("r", F.rank().over(w)).filter("r <= 3").select("c_nationkey", "c_custkey", "r")


@entry("op_win_running", f"select bucket, n, sum(n) over (order by bucket)::bigint as running from (select {ladder_sql('greatest(deg1, deg2)', LAM)} as bucket, sum(deg1 * deg2)::bigint as n from {_DEG} group by 1)")
def win_running(s, d):
    """Running join size over buckets: at most 64 rows, one aggregate below the window."""
    from ..operators.partition import bucket_of

    per = degree_table(load(s, d, TWO)).groupBy(bucket_of(F.greatest("deg1", "deg2"), LAM).alias("bucket")).agg(F.sum(F.col("deg1") * F.col("deg2")).alias("n"))
    return per.withColumn("running", F.sum("n").over(W.orderBy("bucket")))


@entry("op_win_ntile", "select n_regionkey, n_nationkey, ntile(2) over (partition by n_regionkey order by n_nationkey)::int as half from nation")
def win_ntile(s, d):
    return t(s, d, "nation").select("n_regionkey", "n_nationkey", F.ntile(2).over(W.partitionBy("n_regionkey").orderBy("n_nationkey")).alias("half"))


@entry("op_win_lag", "select c_nationkey, c_mktsegment, n, coalesce(n - lag(n) over (partition by c_nationkey order by c_mktsegment), 0)::bigint as gap from (select c_nationkey, c_mktsegment, count(*)::bigint as n from customer group by 1, 2)")
def win_lag(s, d):
    per = t(s, d, "customer").groupBy("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))
    return per.withColumn("gap", F.coalesce(F.col("n") - F.lag("n").over(W.partitionBy("c_nationkey").orderBy("c_mktsegment")), F.lit(0)))


@entry("op_win_range_frame", "select event_type, day, n, sum(n) over (partition by event_type order by day range between 2 preceding and current row)::bigint as three_days from (select event_type, floor(epoch(ts) / 86400)::bigint as day, count(*)::bigint as n from events group by 1, 2)")
def win_range(s, d):
    per = t(s, d, "events").groupBy("event_type", F.floor(F.unix_timestamp("ts") / 86400).alias("day")).agg(F.count("*").alias("n"))
    return per.withColumn("three_days", F.sum("n").over(W.partitionBy("event_type").orderBy("day").rangeBetween(-2, 0)))


@entry("op_topk", f"select K, (deg1 * deg2)::bigint as n from {_DEG} order by n desc, K limit 10")
def topk(s, d):
    return degree_table(load(s, d, TWO)).select("K", (F.col("deg1") * F.col("deg2")).alias("n")).orderBy(F.desc("n"), "K").limit(10)


_SETS = {"union": "select c_custkey as K from customer union select user_id from events", "intersect": "select o_custkey as K from orders intersect select user_id from events", "except": "select c_custkey as K from customer except select user_id from events"}
for _name, _text in _SETS.items():
    def _set(s, d, name=_name):
        key = lambda tab, c: t(s, d, tab).select(F.col(c).alias("K"))
        a, b = key("orders" if name == "intersect" else "customer", "o_custkey" if name == "intersect" else "c_custkey"), key("events", "user_id")
        return {"union": lambda: a.union(b).distinct(), "intersect": lambda: a.intersect(b), "except": lambda: a.subtract(b)}[name]()

    entry(f"op_{_name}", _text)(_set)


# Functions ----------------------------------------------------------------------------------------


@entry("op_string", "select upper(split_part(p_brand, '#', 1)) as brand, split_part(p_brand, '#', 2)::int as number, length(p_type)::int as type_length, count(*)::bigint as n from part group by all")
def strings(s, d):
    return t(s, d, "part").groupBy(F.upper(F.split_part("p_brand", F.lit("#"), F.lit(1))).alias("brand"), F.split_part("p_brand", F.lit("#"), F.lit(2)).cast("int").alias("number"), F.length("p_type").alias("type_length")).agg(F.count("*").alias("n"))


@entry("op_regex", "select regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) as host, count(*)::bigint as n from pages group by 1")
def regex(s, d):
    return t(s, d, "pages").groupBy(F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("host")).agg(F.count("*").alias("n"))


@entry("op_md5_prf", f"select K, u from (select c_custkey as K, {uniform_sql(chr(39) + 'prf' + chr(39), 'c_custkey')} as u from customer)")
def prf(s, d):
    return t(s, d, "customer").select(F.col("c_custkey").alias("K"), noise.uniform_col(SEED, "prf", F.col("c_custkey").cast("string")).alias("u"))


@entry("op_math", f"select K, round(exp(-deg1 / 10.0), 8) as e, round(ln(1 + deg2), 8) as l, round(sqrt(deg1 * deg2), 8) as r, greatest(deg1, deg2)::bigint as g, least(deg1, deg2)::bigint as s, sign(deg1 - deg2)::double as sg from {_DEG}")
def maths(s, d):
    return degree_table(load(s, d, TWO)).select("K", F.round(F.exp(-F.col("deg1") / 10.0), 8).alias("e"), F.round(F.log(1 + F.col("deg2")), 8).alias("l"), F.round(F.sqrt(F.col("deg1") * F.col("deg2")), 8).alias("r"), F.greatest("deg1", "deg2").alias("g"), F.least("deg1", "deg2").alias("s"), F.signum(F.col("deg1") - F.col("deg2")).alias("sg"))


@entry("op_array_config", f"select K, {ladder_sql('deg1', LAM)}::int as first, {ladder_sql('deg2', LAM)}::int as last, 2::int as length from {_DEG}")
def array_config(s, d):
    from ..operators.partition import bucket_of

    config = F.array(bucket_of(F.col("deg1"), LAM), bucket_of(F.col("deg2"), LAM))
    return degree_table(load(s, d, TWO)).withColumn("config", config).select("K", F.element_at("config", 1).alias("first"), F.element_at("config", -1).alias("last"), F.size("config").alias("length"))


@entry("op_array_hof", "select o_custkey, sum(n * w)::bigint as weighted, count(*)::int as present from (select o_custkey, o_orderpriority, count(*) as n, left(o_orderpriority, 1)::int as w from orders group by 1, 2) group by 1")
def array_hof(s, d):
    per = t(s, d, "orders").groupBy("o_custkey", "o_orderpriority").agg(F.count("*").alias("n")).groupBy("o_custkey").agg(F.collect_list(F.struct("o_orderpriority", "n")).alias("v"))
    weight = F.aggregate(F.transform("v", lambda x: x.n * F.substring(x.o_orderpriority, 1, 1).cast("bigint")), F.lit(0).cast("bigint"), lambda a, b: a + b)
    return per.select("o_custkey", weight.alias("weighted"), F.size("v").alias("present"))


@entry("op_map_weights", "select event_type, round(sum(case event_type when 'view' then 0.1 when 'click' then 0.5 when 'purchase' then 1.0 else 0.0 end), 4) as w from events group by 1")
def map_weights(s, d):
    weights = F.map_from_arrays(F.array(*map(F.lit, ("view", "click", "purchase"))), F.array(*map(F.lit, (0.1, 0.5, 1.0))))
    per = t(s, d, "events").groupBy("event_type").agg(F.count("*").alias("n"))
    return per.select("event_type", F.round(F.col("n") * F.coalesce(F.element_at(weights, F.col("event_type")), F.lit(0.0)), 4).alias("w"))


@entry("op_json_props", "select json_extract_string(props, '$.k')::int as k, count(*)::bigint as n from events group by 1")
def json_props(s, d):
    return t(s, d, "events").groupBy(F.from_json("props", "k int").getField("k").alias("k")).agg(F.count("*").alias("n"))


@entry("op_nested_embedding", "select label, (embedding[1] >= 0) as positive, count(*)::bigint as n from embeddings group by 1, 2")
def nested(s, d):
    return t(s, d, "embeddings").groupBy("label", (F.element_at("embedding", 1) >= 0).alias("positive")).agg(F.count("*").alias("n"))


@entry("op_conv_roles", "select role, least(8, n // 2)::bigint as bin, count(*)::bigint as turns from conversations join (select conv_id as c, count(*) as n from conversations group by 1) on c = conv_id group by 1, 2")
def conv_roles(s, d):
    conv = t(s, d, "conversations").select("conv_id", "role")
    size = conv.groupBy("conv_id").agg(F.count("*").alias("n"))
    return conv.join(size, "conv_id").groupBy("role", F.least(F.lit(8), F.floor(F.col("n") / 2)).alias("bin")).agg(F.count("*").alias("turns"))


@entry("op_sql_view_answer", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 2, "select P, round(sum(m * case when E = 'view' then 1.0 else 0.0 end), 2) as views from cells_2 group by P"))
def sql_view(s, d):
    release.release_two_table(load(s, d, TWO), two_queries(), d, EPS, DELTA, ZERO, rounds=2, out="last").view("synthetic_two")
    return s.sql("select P, round(sum(mass * case when E = :event then 1.0 else 0.0 end), 2) as views from synthetic_two group by P", args={"event": "view"})


# UDFs ---------------------------------------------------------------------------------------------


@entry("op_udf_kernel", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 2, "select round(sum(m), 3) as total, count(*)::bigint as cells from cells_2"))
def udf_kernel(s, d):
    """The grouped-map kernel on two sub-instances at once; the first is returned."""
    inst = load(s, d, TWO)
    plan, volume = release.kernel_plan(inst, two_queries(), d)
    from ..queries import answers, dense_answers

    truth = dense_answers(answers(inst, two_queries()).collect(), two_queries())
    rows = [(name, float(truth.flat[0]) * k, 1.0, (truth * k).ravel().tolist(), [volume] * len(plan.points)) for name, k in (("a", 1.0), ("b", 2.0))]
    out = kernel.release_groups(s.createDataFrame(rows, kernel.STATS), plan, kernel.KernelSettings(EPS, DELTA, ZERO, 2))
    return out.filter("sub_id = 'a'").agg(F.round(F.sum("mass"), 3).alias("total"), F.count("*").alias("cells"))


@entry("op_udaf_logsumexp", "select c_mktsegment, round(max(x) + ln(sum(exp(x - m))), 6) as lse from (select c_mktsegment, c_acctbal / 1000 as x, max(c_acctbal / 1000) over (partition by c_mktsegment) as m from customer) group by 1")
def udaf(s, d):
    """Log-sum-exp as two built-in aggregates over a mergeable state: no group is gathered in a task."""
    x = F.col("c_acctbal") / 1000
    top = t(s, d, "customer").groupBy("c_mktsegment").agg(F.max(x).alias("m"))
    return t(s, d, "customer").join(F.broadcast(top), "c_mktsegment").groupBy("c_mktsegment").agg(F.round(F.max("m") + F.log(F.sum(F.exp(x - F.col("m")))), 6).alias("lse"))


@entry("op_udaf_logsumexp_pandas", "select c_mktsegment, c_nationkey, round(max(x) + ln(sum(exp(x - m))), 6) as lse from (select c_mktsegment, c_nationkey, c_acctbal / 1000 as x, max(c_acctbal / 1000) over (partition by c_mktsegment, c_nationkey) as m from customer) group by 1, 2")
def udaf_pandas(s, d):
    @F.pandas_udf("double")
    def logsumexp(x: pd.Series) -> float:
        return float(x.max() + np.log(np.exp(x - x.max()).sum()))

    rows = t(s, d, "customer").select("c_mktsegment", "c_nationkey", (F.col("c_acctbal") / 1000).alias("x"))
    return rows.groupBy("c_mktsegment", "c_nationkey").agg(logsumexp("x").alias("lse")).select("c_mktsegment", "c_nationkey", F.round("lse", 6).alias("lse"))


@entry("op_udf_tlap_scalar", "select count(*)::bigint as n, true as equal from customer")
def udf_tlap(s, d):
    """A vectorised scalar UDF of the truncated-Laplace inverse against its column expression."""

    @F.pandas_udf("double")
    def tlap(u: pd.Series) -> pd.Series:
        return u.map(lambda x: noise.tlap_value(2.0, 28.0, x))

    u = t(s, d, "customer").select(noise.uniform_col(SEED, "udf", F.col("c_custkey").cast("string")).alias("u"))
    both = u.select(tlap("u").alias("a"), noise.tlap_col(2.0, 28.0, F.col("u")).alias("b"))
    return both.agg(F.count("*").alias("n"), (F.max(F.abs(F.col("a") - F.col("b"))) < 1e-9).alias("equal"))


class ExpandCell:
    """Rows of one cell, numbered from 1."""

    def eval(self, name: str, n: int) -> Iterator[tuple[str, int]]:
        for i in range(n or 0):
            yield name, i + 1


@entry("op_udtf_expand", "select c_mktsegment as name, unnest(range(1, 1 + count(*) // 10))::int as i from customer group by c_mktsegment")
def udtf(s, d):
    s.udtf.register("expand_cell", F.udtf(ExpandCell, returnType="name string, i int"))
    t(s, d, "customer").groupBy("c_mktsegment").agg(F.floor(F.count("*") / 10).cast("int").alias("n")).createOrReplaceTempView("joinsynth_segments")
    return s.sql("select e.name, e.i from joinsynth_segments, lateral expand_cell(c_mktsegment, n) e")


# Streams ------------------------------------------------------------------------------------------


def _run(s, d, name, build, mode="append"):
    import uuid

    frame = build(stream.read_events(s, d))
    return stream.run_available(frame, f"{name}_{uuid.uuid4().hex[:8]}", mode, shared_folder(s))


@entry("op_stream_tumbling", "select date_trunc('day', ts) as start, event_type, count(*)::bigint as freq from events group by 1, 2")
def stream_tumbling(s, d):
    return _run(s, d, "tumbling", stream.tumbling, "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@entry("op_stream_sliding", "select start, count(*)::bigint as freq from (select unnest([time_bucket(interval 12 hours, ts), time_bucket(interval 12 hours, ts) - interval 12 hours]) as start from events) group by 1")
def stream_sliding(s, d):
    return _run(s, d, "sliding", stream.sliding, "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@entry("op_stream_session", "select user_id, min(ts) as start, count(*)::bigint as freq from (select user_id, ts, sum(fresh) over (partition by user_id order by ts, event_id rows unbounded preceding) as g from (select user_id, ts, event_id, case when ts < lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minutes then 0 else 1 end as fresh from events)) group by user_id, g")
def stream_session(s, d):
    return _run(s, d, "session", stream.sessions, "complete").withColumn("start", F.col("start").cast("timestamp_ntz"))


@entry("op_stream_dedup", "select count(distinct event_id)::bigint as n from events")
def stream_dedup(s, d):
    return _run(s, d, "dedup", lambda e: stream.dedup(e).select("event_id")).agg(F.count("*").alias("n"))


@entry("op_stream_join", "select b.user_id, a.event_id as click_id, b.event_id as buy_id from events a join events b on a.user_id = b.user_id and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour where a.event_type = 'click' and b.event_type = 'purchase'")
def stream_join(s, d):
    return _run(s, d, "interval", stream.click_to_purchase)


@entry("op_stream_static_join", "select c_mktsegment, count(*)::bigint as n from events join customer on c_custkey = user_id group by 1")
def stream_static(s, d):
    return _run(s, d, "static", lambda e: stream.with_segment(e, t(s, d, "customer")).select("c_mktsegment")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@entry("op_stream_state", "select user_id, least(60, count(*))::bigint as degree from events group by 1")
def stream_state(s, d):
    return _run(s, d, "state", lambda e: stream.capped_degrees(e, 60), "update").groupBy("user_id").agg(F.max("degree").alias("degree"))


@entry("op_stream_late")
def stream_late(s, d):
    """Rows behind the watermark are dropped: windows emitted in append mode against the rows that came."""
    return _run(s, d, "late", stream.tumbling, "append").agg(F.sum("freq").alias("emitted"), F.count("*").alias("windows"))
