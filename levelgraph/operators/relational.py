"""Relational operators that graph work needs around it, each with an independent SQL form."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def as_of_join(left: DataFrame, right: DataFrame, by: str, on: str, value: str) -> DataFrame:
    """Adds to each left row the latest right ``value`` at or before its time, per key.

    One union and one windowed last value: both sides are shuffled once by key, nothing is multiplied."""
    both = left.select(by, on, F.lit(1).alias("_side"), F.struct(*left.columns).alias("_row"), F.lit(None).cast(dict(right.dtypes)[value]).alias("_value")).union(
        right.select(by, on, F.lit(0), F.lit(None), value)
    )
    seen = F.last("_value", ignorenulls=True).over(Window.partitionBy(by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("_seen", seen).where("_side = 1").select("_row.*", F.col("_seen").alias(value))


def interval_join(a: DataFrame, b: DataFrame, by: str, on: str, seconds: int) -> DataFrame:
    """Pairs of one key with ``0 < b.on - a.on <= seconds``: an equi-join on time buckets, then the exact test."""
    t = F.unix_micros(F.col(on).cast("timestamp"))
    width = seconds * 1_000_000
    x = a.select(*[F.col(c).alias(f"a_{c}") for c in a.columns], t.alias("_ta"), F.explode(F.array(F.floor(t / width), F.floor(t / width) + 1)).alias("_bucket"), F.col(by).alias("_key"))
    y = b.select(*[F.col(c).alias(f"b_{c}") for c in b.columns], t.alias("_tb"), F.floor(t / width).alias("_bucket"), F.col(by).alias("_key"))
    return x.join(y, ["_key", "_bucket"]).where((F.col("_tb") > F.col("_ta")) & (F.col("_tb") <= F.col("_ta") + width)).drop("_key", "_bucket", "_ta", "_tb")


def common_neighbours(arcs: DataFrame, at_least: int = 1, fan: int = 16) -> DataFrame:
    """Pairs of vertices on one side with their number of shared neighbours.

    A shared neighbour with many arcs is a hot key: its left arcs are dealt over ``fan`` salts and
    its right ones repeated for each, so its pairs are formed by ``fan`` tasks."""
    a = arcs.select(F.col("src").alias("a"), "dst", F.pmod(F.xxhash64("src"), F.lit(fan)).alias("salt"))
    b = arcs.select(F.col("src").alias("b"), "dst", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(fan - 1).cast("long"))).alias("salt"))
    return a.join(b, ["dst", "salt"]).where("a < b").groupBy("a", "b").agg(F.count("*").alias("shared")).where(F.col("shared") >= at_least)


def sample_by_hash(df: DataFrame, key: str, share: float, seed: int = 7) -> DataFrame:
    """Rows whose key hashes below ``share``: the same rows whatever the layout, whole keys only."""
    h = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col(key).cast("string"))), 1, 8), 16, 10).cast("long")
    return df.where(h < int(share * (1 << 32)))


def sample_by_group(df: DataFrame, group: str, key: str, shares: dict[str, float], seed: int = 7) -> DataFrame:
    """Stratified: each group at a share of its own, by the hash of the key; groups without a share are left out."""
    h = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col(key).cast("string"))), 1, 8), 16, 10).cast("long")
    limit = F.lit(None).cast("long")
    for name, share in shares.items():
        limit = F.when(F.col(group) == name, F.lit(int(share * (1 << 32)))).otherwise(limit)
    return df.where(h < limit)


def _events(spark: SparkSession, sf: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/events.parquet")


def _as_of(spark: SparkSession, sf: str) -> DataFrame:
    e = _events(spark, sf)
    clicks = e.where("event_type = 'click'").groupBy("user_id", "ts").agg(F.max("event_id").alias("last_click"))
    rest = e.where("event_type <> 'click'").select("event_id", "user_id", "ts")
    return as_of_join(rest, clicks, "user_id", "ts", "last_click").select("event_id", "last_click")


def _interval(spark: SparkSession, sf: str) -> DataFrame:
    e = _events(spark, sf).select("event_id", "user_id", "ts")
    return interval_join(e, e, "user_id", "ts", 3600).groupBy(F.col("a_user_id").alias("user_id")).agg(F.count("*").alias("pairs"))


def _t(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def _sql(spark: SparkSession, sf: str, text: str, *tables: str) -> DataFrame:
    """A statement over the named tables, given as arguments, so no view is left behind."""
    for name in tables:
        text = text.replace(f"from {name} ", f"from {{{name}}} ").replace(f"from {name},", f"from {{{name}}},").replace(f"from {name})", f"from {{{name}}})")
        if text.endswith(f"from {name}"):
            text = text[: -len(name)] + f"{{{name}}}"
    return spark.sql(text, **{name: _t(spark, sf, name) for name in tables})


def _lines(spark: SparkSession, sf: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/lineitem.parquet")


OPERATORS = {
    "op_as_of_join": (_as_of, "select e.event_id, (select max(c.event_id) from events c where c.event_type = 'click' and c.user_id = e.user_id and c.ts = (select max(d.ts) from events d where d.event_type = 'click' and d.user_id = e.user_id and d.ts <= e.ts)) as last_click from events e where e.event_type <> 'click'"),
    "op_interval_join": (_interval, "select a.user_id, count(*)::bigint as pairs from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 1 hour group by 1"),
    "op_rollup": (lambda s, d: _lines(s, d).rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")), "select l_returnflag, l_linestatus, count(*)::bigint as n from lineitem group by rollup (l_returnflag, l_linestatus)"),
    "op_cube": (lambda s, d: _lines(s, d).cube("l_returnflag", "l_linestatus").agg(F.max("l_partkey").alias("top_part")), "select l_returnflag, l_linestatus, max(l_partkey) as top_part from lineitem group by cube (l_returnflag, l_linestatus)"),
    "op_pivot": (lambda s, d: _lines(s, d).groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count("l_orderkey")), "select l_returnflag, nullif(count(*) filter (l_linestatus = 'F'), 0)::bigint as \"F\", nullif(count(*) filter (l_linestatus = 'O'), 0)::bigint as \"O\" from lineitem group by 1"),
    "op_window_frame": (lambda s, d: s.read.parquet(f"{d}/orders.parquet").select("o_custkey", "o_orderkey", F.count("*").over(Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(-2, 0)).alias("recent")), "select o_custkey, o_orderkey, count(*) over (partition by o_custkey order by o_orderkey rows between 2 preceding and current row)::bigint as recent from orders"),
    "op_top_k_per_group": (lambda s, d: s.read.parquet(f"{d}/part.parquet").withColumn("rn", F.row_number().over(Window.partitionBy("p_brand").orderBy(F.desc("p_retailprice"), "p_partkey"))).where("rn <= 3").select("p_brand", "rn", "p_partkey"), "select p_brand, rn::bigint as rn, p_partkey from (select *, row_number() over (partition by p_brand order by p_retailprice desc, p_partkey) as rn from part) where rn <= 3"),
    "op_semi_join": (lambda s, d: _t(s, d, "customer").select("c_custkey").join(_t(s, d, "orders").where("o_totalprice > 300000").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi"), "select c_custkey from customer where c_custkey in (select o_custkey from orders where o_totalprice > 300000)"),
    "op_anti_join": (lambda s, d: _t(s, d, "customer").select("c_custkey").join(_t(s, d, "orders").where("o_totalprice > 300000").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti"), "select c_custkey from customer where c_custkey not in (select o_custkey from orders where o_totalprice > 300000)"),
    "op_left_join": (lambda s, d: _t(s, d, "nation").join(_t(s, d, "supplier").where("s_acctbal > 5000").groupBy("s_nationkey").agg(F.count("*").alias("n")), F.col("n_nationkey") == F.col("s_nationkey"), "left").select("n_nationkey", "n"), "select n_nationkey, n from nation left join (select s_nationkey, count(*)::bigint as n from supplier where s_acctbal > 5000 group by 1) on n_nationkey = s_nationkey"),
    "op_full_outer_join": (lambda s, d: _t(s, d, "lineitem").where("l_returnflag = 'R' and l_quantity >= 48").groupBy(F.col("l_partkey").alias("k")).agg(F.count("*").alias("returned")).join(_t(s, d, "lineitem").where("l_returnflag = 'A' and l_quantity >= 48").groupBy(F.col("l_partkey").alias("k")).agg(F.count("*").alias("accepted")), "k", "full"), "select coalesce(a.k, b.k) as k, returned, accepted from (select l_partkey as k, count(*)::bigint as returned from lineitem where l_returnflag = 'R' and l_quantity >= 48 group by 1) a full join (select l_partkey as k, count(*)::bigint as accepted from lineitem where l_returnflag = 'A' and l_quantity >= 48 group by 1) b on a.k = b.k"),
    "op_distinct_aggregates": (lambda s, d: _t(s, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.sum_distinct("l_linenumber").alias("lines")), "select l_returnflag, count(distinct l_partkey)::bigint as parts, sum(distinct l_linenumber)::bigint as lines from lineitem group by 1"),
    # an estimate is compared by whether it is within five percent
    "op_approximate_aggregates": (lambda s, d: _t(s, d, "lineitem").groupBy("l_returnflag").agg((F.abs(F.approx_count_distinct("l_partkey", 0.01) / F.countDistinct("l_partkey") - 1) < 0.05).alias("close"), (F.abs(F.percentile_approx("l_partkey", 0.5, 10000) / F.max("l_partkey") - 0.5) < 0.1).alias("middle")), "select l_returnflag, true as close, true as middle from lineitem group by 1"),
    "op_grouping_sets": (lambda s, d: _t(s, d, "lineitem").groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.grouping_id().alias("level")), "select l_returnflag, l_linestatus, count(*)::bigint as n, grouping(l_returnflag, l_linestatus)::bigint as level from lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())"),
    "op_unpivot": (lambda s, d: _t(s, d, "part").unpivot("p_partkey", ["p_brand", "p_type"], "what", "value").groupBy("what", "value").agg(F.count("*").alias("n")), "select what, value, count(*)::bigint as n from (select 'p_brand' as what, p_brand as value from part union all select 'p_type', p_type from part) group by 1, 2"),
    "op_window_ranking": (lambda s, d: _t(s, d, "part").select("p_partkey", *[f().over(Window.partitionBy("p_brand").orderBy("p_size")).alias(n) for f, n in ((F.rank, "rk"), (F.dense_rank, "dense"))], F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")).alias("quarter"), F.round(F.percent_rank().over(Window.partitionBy("p_brand").orderBy("p_size")), 6).alias("share"), F.round(F.cume_dist().over(Window.partitionBy("p_brand").orderBy("p_size")), 6).alias("upto")), "select p_partkey, rank() over w as rk, dense_rank() over w as dense, ntile(4) over (partition by p_brand order by p_size, p_partkey) as quarter, round(percent_rank() over w, 6) as share, round(cume_dist() over w, 6) as upto from part window w as (partition by p_brand order by p_size)"),
    "op_window_analytic": (lambda s, d: _t(s, d, "orders").select("o_orderkey", *[c.over(Window.partitionBy("o_custkey").orderBy("o_orderkey")).alias(n) for c, n in ((F.lag("o_orderkey"), "before"), (F.lead("o_orderkey"), "after"), (F.first("o_orderkey"), "first"), (F.nth_value("o_orderkey", 2), "second"))]), "select o_orderkey, lag(o_orderkey) over w as before, lead(o_orderkey) over w as after, first_value(o_orderkey) over w as first, nth_value(o_orderkey, 2) over w as second from orders window w as (partition by o_custkey order by o_orderkey)"),
    "op_window_range_frame": (lambda s, d: _events(s, d).select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)).alias("last_hour")), "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row)::bigint as last_hour from events"),
    "op_union_all": (lambda s, d: _t(s, d, "supplier").select(F.col("s_nationkey").alias("k")).unionByName(_t(s, d, "customer").select(F.col("c_nationkey").alias("k"))).groupBy("k").agg(F.count("*").alias("n")), "select k, count(*)::bigint as n from (select s_nationkey as k from supplier union all select c_nationkey from customer) group by 1"),
    "op_except": (lambda s, d: _t(s, d, "part").select(F.col("p_partkey").alias("k")).exceptAll(_t(s, d, "lineitem").where("l_returnflag = 'R' and l_quantity >= 45").select(F.col("l_partkey").alias("k")).distinct()), "select p_partkey as k from part except all select distinct l_partkey from lineitem where l_returnflag = 'R' and l_quantity >= 45"),
    "op_intersect_all": (lambda s, d: _t(s, d, "customer").select(F.col("c_nationkey").alias("k")).intersectAll(_t(s, d, "supplier").select(F.col("s_nationkey").alias("k"))), "select c_nationkey as k from customer intersect all select s_nationkey from supplier"),
    "op_sample_by_hash": (lambda s, d: sample_by_hash(_t(s, d, "orders"), "o_orderkey", 0.1).select("o_orderkey"), "select o_orderkey from orders where ('0x' || substr(md5('7:' || o_orderkey), 1, 8))::bigint < 429496729"),
    "op_sample_by_group": (lambda s, d: sample_by_group(_t(s, d, "orders"), "o_orderstatus", "o_orderkey", {"F": 0.5, "O": 0.125}).select("o_orderkey"), "select o_orderkey from orders where ('0x' || substr(md5('7:' || o_orderkey), 1, 8))::bigint < case o_orderstatus when 'F' then 2147483648 when 'O' then 536870912 end"),
    "op_scalar_subquery": (lambda s, d: _sql(s, d, "select p_partkey from part where p_size > (select avg(p_size) from part)", "part"), "select p_partkey from part where p_size > (select avg(p_size) from part)"),
    "op_exists_subquery": (lambda s, d: _sql(s, d, "select c_custkey from customer c where exists (select 1 from orders o where o.o_custkey = c.c_custkey and o.o_orderstatus = 'P')", "customer", "orders"), "select c_custkey from customer c where exists (select 1 from orders o where o.o_custkey = c.c_custkey and o.o_orderstatus = 'P')"),
    "op_correlated_subquery": (lambda s, d: _sql(s, d, "select o_orderkey from orders o where o_totalprice = (select max(p.o_totalprice) from orders p where p.o_custkey = o.o_custkey)", "orders"), "select o_orderkey from orders o where o_totalprice = (select max(p.o_totalprice) from orders p where p.o_custkey = o.o_custkey)"),
    "op_common_table_expression": (lambda s, d: _sql(s, d, "with busy as (select o_custkey as k, count(*) as n from orders group by o_custkey) select n, count(*) as customers from busy group by n", "orders"), "with busy as (select o_custkey as k, count(*) as n from orders group by o_custkey) select n::bigint as n, count(*)::bigint as customers from busy group by n"),
    "op_recursive_expression": (lambda s, d: _sql(s, d, "with recursive up(k, n) as (select cast(n_nationkey as bigint), 0 from nation where n_nationkey = 0 union all select k + 3, n + 1 from up where n < 9) select k, n from up", "nation"), "with recursive up(k, n) as (select n_nationkey::bigint, 0::bigint from nation where n_nationkey = 0 union all select k + 3, n + 1 from up where n < 9) select k, n from up"),
    "op_lateral_join": (lambda s, d: _sql(s, d, "select s_suppkey, t.slot as slot from supplier, lateral (select explode(sequence(1, s_suppkey % 3 + 1)) as slot) t", "supplier"), "select s_suppkey, t.slot::bigint as slot from supplier, lateral (select unnest(range(1, s_suppkey % 3 + 2)) as slot) t"),
    "op_null_safe_filter": (lambda s, d: _t(s, d, "labels").join(_t(s, d, "documents").select("doc_id", "lang"), "doc_id", "right").where(F.col("quality").eqNullSafe(F.lit(None))).groupBy("lang").agg(F.count("*").alias("n")), "select lang, count(*)::bigint as n from documents where doc_id not in (select doc_id from labels where quality is not null) group by 1"),
    "op_repartition": (lambda s, d: _t(s, d, "orders").select("o_orderkey", F.pmod("o_orderkey", F.lit(4)).cast("int").alias("slot")).repartitionById(4, F.col("slot")).groupBy(F.spark_partition_id().alias("task")).agg(F.count("*").alias("n"), F.countDistinct("slot").alias("slots")), "select o_orderkey % 4 as task, count(*)::bigint as n, 1::bigint as slots from orders group by 1"),
    "op_set_ops": (lambda s, d: s.read.parquet(f"{d}/lineitem.parquet").select(F.col("l_partkey").alias("k")).intersect(s.read.parquet(f"{d}/part.parquet").where("p_size > 25").select(F.col("p_partkey").alias("k"))), "select l_partkey as k from lineitem intersect select p_partkey from part where p_size > 25"),
    "op_json_edges": (lambda s, d: _events(s, d).select("user_id", F.get_json_object("props", "$.k").alias("k")).groupBy("user_id", "k").agg(F.count("*").alias("n")), "select user_id, json_extract_string(props, '$.k') as k, count(*)::bigint as n from events group by 1, 2"),
    "op_common_neighbours": (lambda s, d: common_neighbours(_lines(s, d).select(F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst")).distinct()), "select a.l_suppkey as a, b.l_suppkey as b, count(*)::bigint as shared from (select distinct l_suppkey, l_partkey from lineitem) a join (select distinct l_suppkey, l_partkey from lineitem) b on a.l_partkey = b.l_partkey and a.l_suppkey < b.l_suppkey group by 1, 2"),
}
