"""The relational operators that users of the methods need, each over the given tables."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from normgraph.operators import policygen
from normgraph.sources.registry import load_registry
from normgraph.sources.shared import scratch
from normgraph.sources.tables import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
D = "decimal(18,2)"


def query(f):  # noqa: ANN001, ANN201
    QUERIES[f.__name__] = f
    return f


def n(name: str = "n") -> Column:
    return F.count(F.lit(1)).alias(name)


def money(c: str) -> Column:
    return F.col(c).cast(D)


@query
def op_scan_parquet(spark, sf):
    return table(spark, sf, "orders", "o_orderkey", "o_totalprice").agg(n(), F.min("o_orderkey").alias("lo"), F.max("o_orderkey").alias("hi"))


def _round_trip(spark, sf, fmt, **options):
    d = table(spark, sf, "nation")
    path = f"{scratch(spark)}/{fmt}-{uuid.uuid4().hex}"
    d.write.format(fmt).options(**options).save(path)
    return spark.read.format(fmt).options(**options).schema(d.schema).load(path)


@query
def op_scan_json(spark, sf):
    return _round_trip(spark, sf, "json")


@query
def op_scan_csv(spark, sf):
    return _round_trip(spark, sf, "csv", header="true")


@query
def op_scan_orc(spark, sf):
    return _round_trip(spark, sf, "orc")


@query
def op_scan_text(spark, sf):
    path = f"{scratch(spark)}/text-{uuid.uuid4().hex}"
    table(spark, sf, "nation", "n_name").write.text(path)
    return spark.read.text(path).select(F.col("value").alias("n_name"))


@query
def op_scan_registry(spark, sf):
    """A registry by its own data source: aliases of each kind, and the sentences over orders that name an entry of it."""
    from normgraph.sources.registry import RegistrySource

    spark.dataSource.register(RegistrySource)
    entries = spark.read.format("vocabulary_registry").option("name", "star").load().groupBy("kind", "name").agg(n("aliases"))
    named = F.explode(F.array(*[F.struct(F.lit(k).alias("kind"), F.col(c).alias("name")) for k, c in (("class", "gold_class"), ("property", "gold_pred"))]))
    used = policygen.render(spark, sf).select(named.alias("x")).select("x.*").groupBy("kind", "name").agg(n("used"))
    return entries.join(used, ["kind", "name"], "left").groupBy("kind").agg(F.sum("aliases").alias("n"), F.sum(F.coalesce("used", F.lit(0))).alias("n_sentences"))


@query
def op_sink_partitioned(spark, sf):
    path = f"{scratch(spark)}/part-{uuid.uuid4().hex}"
    d = table(spark, sf, "orders", "o_orderkey", "o_orderstatus", "o_totalprice")
    d.repartition("o_orderstatus", F.pmod("o_orderkey", F.lit(4))).write.partitionBy("o_orderstatus").parquet(path)
    return spark.read.parquet(path).where("o_orderstatus = 'F'").agg(n(), F.sum(money("o_totalprice")).alias("total"))


@query
def op_project(spark, sf):
    d = table(spark, sf, "lineitem", "l_orderkey", "l_linenumber", "l_extendedprice", "l_discount", "l_quantity")
    return d.select("l_orderkey", "l_linenumber", (money("l_extendedprice") * (1 - money("l_discount"))).cast("double").alias("net"), F.when(F.col("l_quantity") > 25, "big").otherwise("small").alias("size"))


@query
def op_filter(spark, sf):
    d = table(spark, sf, "orders", "o_orderkey", "o_totalprice", "o_orderstatus", "o_orderpriority")
    return d.where(F.col("o_totalprice").between(10000, 200000) & F.col("o_orderstatus").isin("F", "O") & ~F.col("o_orderpriority").eqNullSafe(F.lit("5-LOW")))


@query
def op_like(spark, sf):
    return table(spark, sf, "documents", "doc_id", "text").where(F.col("text").like("%License%")).select("doc_id")


@query
def op_rlike(spark, sf):
    return table(spark, sf, "documents", "doc_id", "text").where(F.regexp_like("text", F.lit("[Vv]ersion [0-9]"))).select("doc_id")


def orders(spark, sf):
    return table(spark, sf, "orders", "o_orderkey", "o_custkey", "o_totalprice", "o_orderpriority", "o_orderdate")


@query
def op_join_inner(spark, sf):
    per = table(spark, sf, "lineitem", "l_orderkey", "l_extendedprice").groupBy("l_orderkey").agg(F.sum(money("l_extendedprice")).alias("revenue"))
    return orders(spark, sf).join(per, F.col("o_orderkey") == F.col("l_orderkey")).select("o_orderkey", "revenue")


@query
def op_join_merge(spark, sf):
    return orders(spark, sf).join(table(spark, sf, "customer", "c_custkey", "c_mktsegment").hint("merge"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(n())


@query
def op_join_shuffle_hash(spark, sf):
    return orders(spark, sf).join(table(spark, sf, "customer", "c_custkey", "c_nationkey").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_nationkey").agg(n())


@query
def op_join_broadcast(spark, sf):
    s, na, r = table(spark, sf, "supplier", "s_suppkey", "s_nationkey"), table(spark, sf, "nation"), table(spark, sf, "region")
    return s.join(F.broadcast(na), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(n())  # 25 and 5 rows at every scale


@query
def op_join_left(spark, sf):
    per = table(spark, sf, "lineitem", "l_orderkey").groupBy("l_orderkey").agg(n("k"))
    return orders(spark, sf).join(per, F.col("o_orderkey") == F.col("l_orderkey"), "left").select("o_orderkey", F.coalesce("k", F.lit(0)).alias("k"))


@query
def op_join_right(spark, sf):
    c = table(spark, sf, "customer", "c_custkey")
    per = orders(spark, sf).groupBy("o_custkey").agg(n("k"))
    return per.join(c, F.col("o_custkey") == F.col("c_custkey"), "right").select("c_custkey", F.coalesce("k", F.lit(0)).alias("k"))


@query
def op_join_full(spark, sf):
    a = table(spark, sf, "documents", "doc_id").withColumnRenamed("doc_id", "d")
    b = table(spark, sf, "embeddings", "vec_id")
    return a.join(b, F.col("d") == F.col("vec_id"), "full").agg(F.count("d").alias("n_left"), F.count("vec_id").alias("n_right"), n())


@query
def op_join_semi(spark, sf):
    return table(spark, sf, "documents", "doc_id", "lang").join(table(spark, sf, "labels", "doc_id"), "doc_id", "left_semi").groupBy("lang").agg(n())


@query
def op_join_anti(spark, sf):
    return orders(spark, sf).join(table(spark, sf, "lineitem", "l_orderkey"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").select("o_orderkey")


@query
def op_join_cross(spark, sf):
    """Registry properties by region: both sides of a fixed size."""
    p = load_registry(spark, "star").where("kind = 'property'").select("name").distinct()
    return table(spark, sf, "region", "r_name").crossJoin(F.broadcast(p))


@query
def op_join_theta(spark, sf):
    """Supplier pairs of a nation with balances less than 100 apart, by bands of 100 and their neighbours."""
    s = table(spark, sf, "supplier", "s_suppkey", "s_nationkey", "s_acctbal").withColumn("band", F.floor(F.col("s_acctbal") / 100))
    a = s.select(F.col("s_suppkey").alias("a"), F.col("s_nationkey").alias("na"), F.col("s_acctbal").alias("ba"), F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"))
    b = s.select(F.col("s_suppkey").alias("b"), F.col("s_nationkey").alias("nb"), F.col("s_acctbal").alias("bb"), "band")
    return a.join(b, "band").where("na = nb and a < b and abs(ba - bb) < 100").select("a", "b")


BANDS = ((0, "small", 0.0, 50_000.0), (1, "middle", 50_000.0, 150_000.0), (2, "large", 150_000.0, 1e12))


@query
def op_join_range(spark, sf):
    b = spark.createDataFrame(list(BANDS), "band int, name string, lo double, hi double")  # a handful of rows
    return orders(spark, sf).join(F.broadcast(b), (F.col("o_totalprice") >= F.col("lo")) & (F.col("o_totalprice") < F.col("hi"))).groupBy("name").agg(n())


def events(spark, sf):
    return table(spark, sf, "events", "event_id", "ts", "user_id", "event_type", "value").withColumn("ts", F.col("ts").cast("timestamp"))


@query
def op_join_interval(spark, sf):
    """Clicks followed by a purchase of the same user within an hour, by hour buckets."""
    e = events(spark, sf)
    hour = F.floor(F.unix_timestamp("ts") / 3600)
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("ts").alias("t1"), F.explode(F.array(hour, hour + 1)).alias("hour"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("t2"), hour.alias("hour"))
    return c.join(p, ["user_id", "hour"]).where("t2 >= t1 and t2 <= t1 + interval 1 hour").select("click", "purchase")


@query
def op_join_asof(spark, sf):
    """The latest click at or before each purchase of a user: one sort by user, no join."""
    e = events(spark, sf).where("event_type in ('click', 'purchase')")
    is_click = F.col("event_type") == "click"
    w = Window.partitionBy("user_id").orderBy("ts", (~is_click).cast("int"), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("click", F.last(F.when(is_click, F.col("event_id")), ignorenulls=True).over(w)).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "click")


@query
def op_join_self(spark, sf):
    """Texts that several documents share: grouped first, so that copies never make pairs."""
    d = table(spark, sf, "documents", "doc_id", "text").groupBy(F.md5("text").alias("digest")).agg(n(), F.min("doc_id").alias("first"))
    return d.where("n > 1")


@query
def op_agg_basic(spark, sf):
    d = table(spark, sf, "lineitem", "l_returnflag", "l_linestatus", "l_quantity", "l_extendedprice")
    return d.groupBy("l_returnflag", "l_linestatus").agg(n(), F.sum(money("l_quantity")).alias("qty"), F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi"), F.round(F.avg("l_quantity"), 6).alias("mean"))


@query
def op_agg_distinct(spark, sf):
    return orders(spark, sf).groupBy("o_orderpriority").agg(F.count_distinct("o_custkey").alias("customers"))


@query
def op_agg_filter(spark, sf):
    return table(spark, sf, "labels", "quality", "toxic").groupBy("quality").agg(F.count_if(F.col("toxic") == 1).alias("toxic"), n())


def geography(spark, sf):
    c, na, r = table(spark, sf, "customer", "c_nationkey", "c_acctbal", "c_mktsegment"), table(spark, sf, "nation"), table(spark, sf, "region")
    return c.join(F.broadcast(na), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).select("r_name", "n_name", "c_mktsegment", money("c_acctbal").alias("bal"))


@query
def op_agg_rollup(spark, sf):
    return geography(spark, sf).rollup("r_name", "n_name").agg(F.sum("bal").alias("bal"), F.grouping_id().cast("int").alias("level"))


@query
def op_agg_cube(spark, sf):
    return geography(spark, sf).cube("r_name", "c_mktsegment").agg(F.sum("bal").alias("bal"), n())


@query
def op_agg_sets(spark, sf):
    g = geography(spark, sf)
    return g.groupingSets([["r_name"], ["c_mktsegment"], []], "r_name", "c_mktsegment").agg(n())


@query
def op_agg_pivot(spark, sf):
    d = table(spark, sf, "lineitem", "l_returnflag", "l_linestatus")
    return d.groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(n()).select("l_returnflag", F.coalesce("F", F.lit(0)).alias("n_f"), F.coalesce("O", F.lit(0)).alias("n_o"))


@query
def op_agg_unpivot(spark, sf):
    d = table(spark, sf, "customer", "c_custkey", "c_name", "c_mktsegment")
    return d.unpivot("c_custkey", ["c_name", "c_mktsegment"], "attribute", "value")


@query
def op_agg_percentile(spark, sf):
    d = table(spark, sf, "events", "event_type", "value")
    return d.groupBy("event_type").agg(F.round(F.percentile("value", F.lit(0.5)), 9).alias("median"), F.max("value").alias("hi"))


@query
def op_agg_approx(spark, sf):
    """Within its error of the exact count: true for every type."""
    d = table(spark, sf, "events", "event_type", "user_id")
    return d.groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.count_distinct("user_id").alias("e")).select("event_type", (F.abs(F.col("a") - F.col("e")) <= 0.1 * F.col("e") + 1).alias("close"))


@query
def op_agg_sketch(spark, sf):
    d = table(spark, sf, "events", "event_type", "user_id").groupBy("event_type").agg(F.hll_sketch_agg("user_id", 12).alias("s"))
    exact = table(spark, sf, "events", "user_id").agg(F.count_distinct("user_id").alias("e"))
    return d.agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("a")).crossJoin(exact).select((F.abs(F.col("a") - F.col("e")) <= 0.1 * F.col("e") + 1).alias("close"))


@query
def op_agg_collect(spark, sf):
    d = table(spark, sf, "orders", "o_custkey", "o_orderpriority")
    return d.groupBy("o_custkey").agg(F.array_join(F.array_sort(F.collect_set("o_orderpriority")), ",").alias("priorities"))


@query
def op_agg_having(spark, sf):
    return table(spark, sf, "lineitem", "l_orderkey").groupBy("l_orderkey").agg(n()).where("n > 5")


@query
def op_agg_bool(spark, sf):
    return table(spark, sf, "customer", "c_nationkey", "c_acctbal").groupBy("c_nationkey").agg(F.bool_or(F.col("c_acctbal") < 0).alias("any_debt"), F.bool_and(F.col("c_acctbal") < 10000).alias("all_low"))


@query
def op_win_rank(spark, sf):
    w = Window.partitionBy("c_mktsegment").orderBy(F.col("c_acctbal").desc(), "c_custkey")
    v = Window.partitionBy("c_mktsegment").orderBy("c_nationkey")
    d = table(spark, sf, "customer", "c_custkey", "c_mktsegment", "c_acctbal", "c_nationkey")
    return d.select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("nt"), F.round(F.percent_rank().over(v), 9).alias("pr"), F.round(F.cume_dist().over(v), 9).alias("cd"))


def per_user():  # noqa: ANN201
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


@query
def op_win_lag(spark, sf):
    e = events(spark, sf)
    return e.select("event_id", F.lag("event_id").over(per_user()).alias("previous"), F.lead("event_type").over(per_user()).alias("next_type"))


@query
def op_win_frame_rows(spark, sf):
    return events(spark, sf).select("event_id", F.round(F.avg("value").over(per_user().rowsBetween(-6, 0)), 6).alias("mean7"))


@query
def op_win_frame_range(spark, sf):
    w = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    return events(spark, sf).withColumn("sec", F.unix_timestamp("ts")).select("event_id", F.count(F.lit(1)).over(w).alias("day_count"))


@query
def op_win_value(spark, sf):
    w = per_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return events(spark, sf).select("event_id", F.first("event_id").over(w).alias("first_id"), F.last("event_id").over(w).alias("last_id"), F.nth_value("event_id", 2).over(w).alias("second_id"))


@query
def op_win_share(spark, sf):
    d = policygen.codes(spark, sf).groupBy("code").agg(n())
    return d.crossJoin(F.broadcast(d.agg(F.sum("n").alias("total")))).select("code", "n", F.round(F.col("n") / F.col("total"), 9).alias("share"))


@query
def op_sort(spark, sf):
    return table(spark, sf, "supplier", "s_suppkey", "s_acctbal").orderBy(F.col("s_acctbal").desc(), "s_suppkey")


@query
def op_topk(spark, sf):
    return table(spark, sf, "customer", "c_custkey", "c_acctbal").orderBy(F.col("c_acctbal").desc(), "c_custkey").limit(10)


@query
def op_offset(spark, sf):
    return table(spark, sf, "customer", "c_custkey", "c_acctbal").orderBy(F.col("c_acctbal").desc(), "c_custkey").offset(10).limit(10)


@query
def op_topk_group(spark, sf):
    w = Window.partitionBy("o_orderpriority").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return orders(spark, sf).withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("o_orderpriority", "o_orderkey", "rn")


def _nations(spark, sf):
    return table(spark, sf, "customer", F.col("c_nationkey").alias("k")), table(spark, sf, "supplier", F.col("s_nationkey").alias("k"))


@query
def op_set_union(spark, sf):
    a, b = _nations(spark, sf)
    return a.union(b).distinct()


@query
def op_set_union_all(spark, sf):
    a, b = _nations(spark, sf)
    return a.unionByName(b).groupBy("k").agg(n())


@query
def op_set_intersect(spark, sf):
    a, b = _nations(spark, sf)
    return a.intersect(b)


@query
def op_set_intersect_all(spark, sf):
    a, b = _nations(spark, sf)
    return a.intersectAll(b).groupBy("k").agg(n())


@query
def op_set_except(spark, sf):
    a, b = _nations(spark, sf)
    return a.where("k % 2 = 0").exceptAll(b.where("k < 0")).distinct().subtract(b.where("k > 20"))


@query
def op_set_except_all(spark, sf):
    a, b = _nations(spark, sf)
    return a.exceptAll(b).groupBy("k").agg(n())


def _views(spark, sf):
    for t in ("orders", "customer", "lineitem", "supplier", "nation"):
        table(spark, sf, t).createOrReplaceTempView(f"_rel_{t}")


@query
def op_subquery_scalar(spark, sf):
    _views(spark, sf)
    return spark.sql("select o_orderkey from _rel_orders where o_totalprice > (select avg(o_totalprice) * 1.8 from _rel_orders)")


@query
def op_subquery_correlated(spark, sf):
    _views(spark, sf)
    return spark.sql("select c_custkey from _rel_customer c where c_acctbal > (select avg(c_acctbal) * 1.9 from _rel_customer d where d.c_mktsegment = c.c_mktsegment)")


@query
def op_subquery_exists(spark, sf):
    _views(spark, sf)
    return spark.sql("select o_orderkey from _rel_orders where exists (select 1 from _rel_lineitem where l_orderkey = o_orderkey and l_discount > 0.09)")


@query
def op_subquery_in(spark, sf):
    _views(spark, sf)
    return spark.sql("select c_custkey from _rel_customer where c_nationkey in (select s_nationkey from _rel_supplier where s_acctbal < 0)")


@query
def op_subquery_notin(spark, sf):
    _views(spark, sf)
    return spark.sql("select n_name from _rel_nation where n_nationkey not in (select s_nationkey from _rel_supplier where s_acctbal > 9000)")


@query
def op_subquery_lateral(spark, sf):
    _views(spark, sf)
    return spark.sql("select n_name, best from _rel_nation, lateral (select max(s_acctbal) as best from _rel_supplier where s_nationkey = n_nationkey)")


@query
def op_cte(spark, sf):
    _views(spark, sf)
    return spark.sql("with a as (select o_custkey, count(*) as n from _rel_orders group by 1), b as (select n, count(*) as customers from a group by 1) select * from b")


@query
def op_recursive_override(spark, sf):
    """Closure of a chain of overrides: nation i overrides nation i + 7; depth is bounded against cycles."""
    _views(spark, sf)
    return spark.sql("""with recursive e as (select n_nationkey as src, n_nationkey + 7 as dst from _rel_nation where n_nationkey + 7 < 25),
      r(src, dst, depth) as (select src, dst, 1 from e union all select r.src, e.dst, depth + 1 from r join e on r.dst = e.src where depth < 10) select src, dst, depth from r""")


@query
def op_sample_hash(spark, sf):
    draw = F.conv(F.substring(F.md5(F.concat(F.lit("42|s|"), F.col("doc_id"))), 1, 8), 16, 10).cast("long") % 100
    return table(spark, sf, "documents", "doc_id").where(draw < 10)


@query
def op_distinct_dedup(spark, sf):
    return table(spark, sf, "documents", "doc_id", "text").groupBy(F.md5("text").alias("digest")).agg(F.min("doc_id").alias("doc_id"))


@query
def op_ngram_contain(spark, sf):
    """Documents that hold an eight-word run of a protected passage: hashes of the passages' runs, semi-joined."""
    words = lambda c: F.filter(F.split(F.lower(c), r"[\x20\x09-\x0D]+"), lambda w: w != "")
    runs = lambda w: F.when(F.size(w) >= 8, F.transform(F.sequence(F.lit(1), F.size(w) - 7), lambda i: F.md5(F.array_join(F.slice(w, i, 8), " "))))
    item = table(spark, sf, "benchmark", "text").select(words(F.col("text")).alias("w")).select(F.explode(runs(F.col("w"))).alias("h")).distinct()
    d = table(spark, sf, "documents", "doc_id", "text").select("doc_id", words(F.col("text")).alias("w"))
    pos = d.where(F.size("w") >= 8).select("doc_id", F.posexplode("w").alias("i", "x"))
    w = Window.partitionBy("doc_id").orderBy("i").rowsBetween(0, 7)
    run = pos.select("doc_id", F.count("x").over(w).alias("k"), F.md5(F.array_join(F.collect_list("x").over(w), " ")).alias("h")).where("k = 8")
    return run.join(item, "h", "left_semi").select("doc_id").distinct()


@query
def op_pii_patterns(spark, sf):
    d = table(spark, sf, "documents", "source", "text")
    return d.groupBy("source").agg(F.sum(F.regexp_count("text", F.lit("[A-Za-z0-9._]+@[A-Za-z0-9.-]+"))).alias("emails"), F.sum(F.regexp_count("text", F.lit("[0-9]{3}-[0-9]{4}"))).alias("phones"))


# ---- functions


@query
def fn_string(spark, sf):
    t = F.col("c_name")
    return table(spark, sf, "customer", "c_custkey", "c_name").select("c_custkey", F.lower(t).alias("a"), F.substring(t, 3, 5).alias("b"), F.translate(t, "abc", "xyz").alias("c"), F.length(t).alias("d"), F.regexp_extract(t, "([0-9]+)", 1).alias("e"), F.regexp_replace(t, "[0-9]+", "#").alias("f"), F.concat_ws("-", F.lit("k"), t).alias("g"), F.levenshtein(t, F.lit("Customer")).alias("h"), F.lpad(F.col("c_custkey").cast("string"), 6, "0").alias("i"), F.reverse(t).alias("j"))


@query
def fn_date(spark, sf):
    d = F.col("o_orderdate").cast("timestamp")
    return table(spark, sf, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.dayofyear(d).alias("doy"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("mon"), F.datediff(d, F.lit("1992-01-01").cast("date")).alias("since"), F.date_format(F.add_months(d, 2), "yyyy-MM-dd").alias("later"), F.quarter(d).alias("q"))


@query
def fn_math(spark, sf):
    x = F.col("l_quantity")
    r = lambda c: F.round(c, 9)
    return table(spark, sf, "lineitem", "l_orderkey", "l_linenumber", "l_quantity", "l_extendedprice").select("l_orderkey", "l_linenumber", "l_extendedprice", r(F.sqrt(x)).alias("a"), r(F.log(x)).alias("b"), r(F.asin(x / 100)).alias("c"), F.floor(x / 7).alias("d"), r(F.pow(x, F.lit(1.5))).alias("e"), F.pmod(x.cast("int"), F.lit(7)).alias("f"), r(F.exp(-x / 10)).alias("g"), F.greatest(x, F.lit(25.0)).alias("h"), F.sign(x - 25).alias("i"))


@query
def fn_array(spark, sf):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return table(spark, sf, "embeddings", "vec_id", "embedding").select("vec_id", F.size(e).alias("n"), F.round(F.aggregate(e, F.lit(0.0), lambda s, x: s + x * x), 6).alias("sq"), F.size(F.filter(e, lambda x: x > 0)).alias("pos"), F.exists(e, lambda x: x > 0.5).alias("big"), F.round(F.array_max(e), 9).alias("hi"), F.round(F.element_at(e, -1), 9).alias("last"), F.round(F.aggregate(F.slice(F.sort_array(e), 1, 3), F.lit(0.0), lambda s, x: s + x), 6).alias("low3"))


@query
def fn_map(spark, sf):
    m = F.create_map(F.lit("seg"), F.col("c_mktsegment"), F.lit("nation"), F.col("c_nationkey").cast("string"))
    kept = F.map_filter(m, lambda k, v: F.length(v) > 2)
    return table(spark, sf, "customer", "c_custkey", "c_mktsegment", "c_nationkey").select("c_custkey", m["seg"].alias("a"), F.size(kept).alias("b"), F.array_join(F.array_sort(F.map_keys(m)), ",").alias("c"))


@query
def fn_json(spark, sf):
    p = F.col("props")
    return table(spark, sf, "events", "event_id", "props").select("event_id", F.from_json(p, "k long")["k"].alias("k"), F.get_json_object(p, "$.k").alias("s"), F.variant_get(F.parse_json(p), "$.k", "long").alias("v"), F.to_json(F.struct(F.col("event_id").alias("id"))).alias("j"))


@query
def fn_struct(spark, sf):
    s = F.struct(F.col("n_nationkey").alias("k"), F.struct(F.col("n_name").alias("name")).alias("inner"))
    return table(spark, sf, "nation").select(s.alias("s")).select(F.col("s.k").alias("k"), F.col("s.inner.name").alias("name"), F.col("s").withField("z", F.lit(1))["z"].alias("z"))


@query
def fn_null(spark, sf):
    x = F.when(F.col("c_acctbal") < 0, F.lit(None)).otherwise(F.col("c_nationkey"))
    return table(spark, sf, "customer", "c_custkey", "c_acctbal", "c_nationkey").select("c_custkey", F.coalesce(x, F.lit(-1)).alias("a"), F.nullif(F.col("c_nationkey"), F.lit(3)).alias("b"), x.isNull().alias("c"), x.eqNullSafe(F.lit(None)).alias("d"), F.nvl2(x, F.lit("some"), F.lit("none")).alias("e"))


@query
def fn_cast(spark, sf):
    t = F.col("p_name")
    return table(spark, sf, "part", "p_partkey", "p_name", "p_retailprice").select("p_partkey", t.try_cast("int").isNull().alias("a"), F.col("p_retailprice").cast("int").alias("b"), F.col("p_retailprice").cast(D).alias("c"), F.col("p_partkey").cast("string").alias("d"), (F.col("p_partkey") % 2).cast("boolean").alias("e"))


@query
def fn_hash(spark, sf):
    return table(spark, sf, "nation", "n_nationkey", "n_name").select("n_nationkey", F.md5("n_name").alias("a"), F.sha2("n_name", 256).alias("b"), F.conv(F.substring(F.md5("n_name"), 1, 8), 16, 10).cast("long").alias("c"), F.hex("n_name").alias("d"), F.base64(F.encode("n_name", "UTF-8")).alias("e"))
