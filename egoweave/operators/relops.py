"""The surrounding relational operators, each as one query with its SQL: (name, sql, function of a table reader)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

OPS: list[tuple[str, str, object]] = []


def op(name: str, sql: str):
    def keep(fn):
        OPS.append((f"op_{name}", sql, fn))
        return fn

    return keep


@op("scan_filter_project", "select l_orderkey, l_partkey, l_quantity * 2 as double_qty from lineitem where l_quantity < 5 and l_returnflag = 'R'")
def _(t):
    return t("lineitem").where("l_quantity < 5 and l_returnflag = 'R'").select("l_orderkey", "l_partkey", (F.col("l_quantity") * 2).alias("double_qty"))


@op("broadcast_join", "select c_custkey, n_name from customer join nation on c_nationkey = n_nationkey")
def _(t):
    # nation has a row a country: bounded by the world, not by the data
    return t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


@op("semi_join", "select p_partkey from part where p_partkey in (select l_partkey from lineitem where l_returnflag = 'R')")
def _(t):
    r = t("lineitem").where("l_returnflag = 'R'").select(F.col("l_partkey").alias("p_partkey"))
    return t("part").join(r, "p_partkey", "left_semi").select("p_partkey")


@op("anti_join", "select p_partkey from part where p_partkey not in (select l_partkey from lineitem where l_quantity > 48)")
def _(t):
    r = t("lineitem").where("l_quantity > 48").select(F.col("l_partkey").alias("p_partkey"))
    return t("part").join(r, "p_partkey", "left_anti").select("p_partkey")


@op("full_outer_join", "select a.k as left_key, b.k as right_key from (select distinct o_custkey as k from orders where o_totalprice > 300000) a full join (select c_custkey as k from customer where c_acctbal > 5000) b on a.k = b.k")
def _(t):
    a = t("orders").where("o_totalprice > 300000").select(F.col("o_custkey").alias("left_key")).distinct()
    return a.join(t("customer").where("c_acctbal > 5000").select(F.col("c_custkey").alias("right_key")), F.col("left_key") == F.col("right_key"), "full")


@op("theta_pairs", "select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_nationkey = b.s_nationkey and a.s_acctbal < b.s_acctbal")
def _(t):
    s = t("supplier").select("s_suppkey", "s_nationkey", "s_acctbal")
    return s.alias("a").join(s.alias("b"), (F.col("a.s_nationkey") == F.col("b.s_nationkey")) & (F.col("a.s_acctbal") < F.col("b.s_acctbal"))).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


@op("interval_join", "select a.event_id as a, b.event_id as b from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts > a.ts and b.ts <= a.ts + interval 1 hour")
def _(t):
    """Keys are the user and the hour; the later event looks in its own hour and the one before, so the range becomes an equi-join."""
    hour = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600)
    e = t("events").select("event_id", "user_id", "event_type", "ts", hour.alias("h"))
    a = e.where("event_type = 'click'").select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("ta"), "h")
    b = e.where("event_type = 'purchase'").select(F.col("event_id").alias("b"), "user_id", F.col("ts").alias("tb"), F.explode(F.array(F.col("h"), F.col("h") - 1)).alias("h"))
    return a.join(b, ["user_id", "h"]).where("tb > ta and tb <= ta + interval 1 hour").select("a", "b")


@op("asof_join", "select event_id, (select max(b.event_id) from events b where b.user_id = a.user_id and b.event_type = 'click' and b.ts = (select max(c.ts) from events c where c.user_id = a.user_id and c.event_type = 'click' and c.ts < a.ts)) as last_click from events a where event_type = 'purchase'")
def _(t):
    """The latest click strictly before each purchase, of clicks at one time the largest id: one sort per user, no self-join."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(Window.unboundedPreceding, -1)
    last = F.max(F.when(F.col("event_type") == "click", F.struct("us", "event_id"))).over(w).event_id
    return t("events").withColumn("us", us).withColumn("last_click", last).where("event_type = 'purchase'").select("event_id", "last_click")


@op("cube_metrics", "select l_returnflag, l_linestatus, count(*) as n from lineitem group by cube (l_returnflag, l_linestatus)")
def _(t):
    return t("lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@op("rollup_orders", "select o_orderstatus, o_orderpriority, count(*) as n from orders group by rollup (o_orderstatus, o_orderpriority)")
def _(t):
    return t("orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@op("grouping_sets", "select c_mktsegment, c_nationkey, count(*) as n from customer group by grouping sets ((c_mktsegment), (c_nationkey))")
def _(t):
    return t("customer").groupingSets([["c_mktsegment"], ["c_nationkey"]], "c_mktsegment", "c_nationkey").agg(F.count("*").alias("n"))


@op("pivot_flags", "select l_linestatus, count(*) filter (l_returnflag = 'A') as a, count(*) filter (l_returnflag = 'N') as n, count(*) filter (l_returnflag = 'R') as r from lineitem group by 1")
def _(t):
    p = t("lineitem").groupBy("l_linestatus").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count(F.lit(1)))
    return p.select("l_linestatus", *(F.coalesce(c, F.lit(0)).alias(c.lower()) for c in "ANR"))


@op("distinct_aggregates", "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers, count(*) as n from lineitem group by 1")
def _(t):
    return t("lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"), F.count("*").alias("n"))


@op("window_rank", "select o_orderkey, rank() over (partition by o_custkey order by o_totalprice desc)::int as r, dense_rank() over (partition by o_custkey order by o_orderdate)::int as dr, ntile(4) over (partition by o_custkey order by o_totalprice, o_orderkey)::int as q from orders")
def _(t):
    w = Window.partitionBy("o_custkey")
    return t("orders").select("o_orderkey", F.rank().over(w.orderBy(F.desc("o_totalprice"))).alias("r"), F.dense_rank().over(w.orderBy("o_orderdate")).alias("dr"), F.ntile(4).over(w.orderBy("o_totalprice", "o_orderkey")).alias("q"))


@op("window_rows_frame", "select o_orderkey, count(*) over w as n, max(o_totalprice) over w as top from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey rows between 2 preceding and current row)")
def _(t):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)
    return t("orders").select("o_orderkey", F.count("*").over(w).alias("n"), F.max("o_totalprice").over(w).alias("top"))


@op("window_range_frame", "select l_orderkey, l_linenumber, l_partkey, count(*) over (partition by l_partkey order by l_quantity range between 5 preceding and 5 following) as n from lineitem")
def _(t):
    w = Window.partitionBy("l_partkey").orderBy("l_quantity").rangeBetween(-5, 5)
    return t("lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.count("*").over(w).alias("n"))


@op("lead_lag", "select event_id, lag(event_id) over w as before, lead(event_id) over w as after from events window w as (partition by user_id order by ts, event_id)")
def _(t):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t("events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"))


@op("topk_per_group", "select s_nationkey, s_suppkey, s_acctbal from supplier qualify row_number() over (partition by s_nationkey order by s_acctbal desc, s_suppkey) <= 2")
def _(t):
    rank = F.row_number().over(Window.partitionBy("s_nationkey").orderBy(F.desc("s_acctbal"), "s_suppkey"))
    return t("supplier").withColumn("r", rank).where("r <= 2").select("s_nationkey", "s_suppkey", "s_acctbal")


@op("union_all", "select c_nationkey as k from customer union all select s_nationkey from supplier")
def _(t):
    return t("customer").select(F.col("c_nationkey").alias("k")).unionAll(t("supplier").select("s_nationkey"))


@op("intersect", "select c_nationkey as k from customer intersect select s_nationkey from supplier")
def _(t):
    return t("customer").select(F.col("c_nationkey").alias("k")).intersect(t("supplier").select("s_nationkey"))


@op("except", "select p_partkey as k from part except select l_partkey from lineitem where l_returnflag = 'R' and l_quantity > 20")
def _(t):
    return t("part").select(F.col("p_partkey").alias("k")).subtract(t("lineitem").where("l_returnflag = 'R' and l_quantity > 20").select("l_partkey"))


@op("string_functions", "select page_id, lower(split_part(url, '/', 3)) as host, length(url) as n, replace(url, 'http', 'H') as r, starts_with(url, 'https') as secure from pages")
def _(t):
    return t("pages").select("page_id", F.lower(F.split_part("url", F.lit("/"), F.lit(3))).alias("host"), F.length("url").cast("bigint").alias("n"), F.replace("url", F.lit("http"), F.lit("H")).alias("r"), F.startswith("url", F.lit("https")).alias("secure"))


@op("date_functions", "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, date_diff('day', date '1995-01-01', o_orderdate::date) as days from orders")
def _(t):
    return t("orders").select("o_orderkey", F.year("o_orderdate").cast("bigint").alias("y"), F.month("o_orderdate").cast("bigint").alias("m"), F.date_diff(F.to_date("o_orderdate"), F.lit("1995-01-01").cast("date")).cast("bigint").alias("days"))


@op("math_bits", "select p_partkey, p_partkey % 7 as m, (p_partkey & 15) | 32 as b, bit_count(p_partkey) as ones, greatest(p_size, 10) as g from part")
def _(t):
    c = F.col("p_partkey")
    return t("part").select("p_partkey", (c % 7).alias("m"), c.bitwiseAND(15).bitwiseOR(32).alias("b"), F.bit_count(c).cast("tinyint").alias("ones"), F.greatest("p_size", F.lit(10)).alias("g"))


@op("array_functions", "select l_orderkey, list_sort(list(distinct l_partkey)) as parts, len(list(distinct l_suppkey)) as n from lineitem group by 1")
def _(t):
    return t("lineitem").groupBy("l_orderkey").agg(F.sort_array(F.collect_set("l_partkey")).alias("parts"), F.size(F.collect_set("l_suppkey")).cast("bigint").alias("n"))


@op("map_functions", "select o_custkey, count(*) filter (o_orderstatus = 'F') as f, count(*) filter (o_orderstatus = 'O') as o from orders group by 1")
def _(t):
    m = t("orders").groupBy("o_custkey", "o_orderstatus").agg(F.count("*").alias("n")).groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "n"))).alias("m"))
    get = lambda k: F.coalesce(F.try_element_at("m", F.lit(k)), F.lit(0))
    return m.select("o_custkey", get("F").alias("f"), get("O").alias("o"))


@op("json_functions", "select event_id, cast(json_extract_string(props, '$.k') as bigint) as k from events")
def _(t):
    return t("events").select("event_id", F.from_json("props", "k bigint").getField("k").alias("k"))


@op("decimal_sum", "select l_returnflag, cast(sum(cast(l_extendedprice as decimal(15, 2))) as double) as total from lineitem group by 1")
def _(t):
    return t("lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(15,2)")).cast("double").alias("total"))


@op("nested_structs", "select c_nationkey, max(c_acctbal) as top, arg_max(c_custkey, c_acctbal) as who from customer group by 1")
def _(t):
    best = t("customer").groupBy("c_nationkey").agg(F.max(F.struct("c_acctbal", "c_custkey")).alias("x"))
    return best.select("c_nationkey", F.col("x.c_acctbal").alias("top"), F.col("x.c_custkey").alias("who"))


def skew_join(left: DataFrame, right: DataFrame, key: str, salts: int = 16, hot: int = 10_000) -> DataFrame:
    """Inner join whose hot keys on the left are dealt over salts; only the rows of those keys are copied on the right."""
    heavy = left.groupBy(key).agg(F.count("*").alias("n")).where(F.col("n") > hot).select(key, F.lit(salts).alias("s"))
    salted = left.join(heavy, key, "left").withColumn("salt", F.when(F.col("s").isNull(), 0).otherwise(F.pmod(F.xxhash64(*left.columns), F.lit(salts)))).drop("s")
    copied = right.join(heavy, key, "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce("s", F.lit(1)) - 1))).drop("s")
    return salted.withColumn("salt", F.col("salt").cast("int")).join(copied, [key, "salt"]).drop("salt")
