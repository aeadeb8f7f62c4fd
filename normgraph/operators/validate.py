"""Shape validation over entity tables, and over triples.

All shapes of one (class, path) share one measured count for each focus node; a path that is a foreign key is one
shuffle join of pre-aggregated counts, a path that is a column predicate needs none.  Focus nodes without a value
count 0, which is what minimum constraints are about.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from normgraph.operators import shapes
from normgraph.sources.tables import table


@dataclass(frozen=True)
class Constraint:
    shape: str
    focus_class: str
    path: str
    min_count: int | None
    max_count: int | None
    severity: str = "Violation"


STAR = (
    Constraint("S1", "Order", "hasLineItem", 1, None),
    Constraint("S2", "Customer", "hasNegativeBalance", None, 0),
    Constraint("S3", "Supplier", "hasNegativeBalance", None, 0),
    Constraint("S4", "OrderSlot", "hasLine", None, 1),
    Constraint("S5", "LineItem", "shippedBeforeOrdered", None, 0),
    Constraint("S6", "Customer", "placesOrder", 1, None),
    Constraint("S7", "LineItem", "hasHighDiscount", None, 0, "Warning"),
    Constraint("S8", "Order", "hasReturnedLine", 1, None),
    Constraint("S9", "Order", "hasLateLine", None, None, "Info"),
)


def paths(spark: SparkSession, sf_dir: str) -> dict[tuple[str, str], DataFrame]:
    """``(focus_id, observed)`` for each (class, path) of the star schema; plans only."""
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    customer = table(spark, sf_dir, "customer", "c_custkey", "c_acctbal")
    lines = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_discount", "l_returnflag", "l_shipdate")
    supplier = table(spark, sf_dir, "supplier", "s_suppkey", "s_acctbal")
    one = F.count(F.lit(1))
    per_order = lines.groupBy("l_orderkey").agg(one.alias("n"), F.count_if(F.col("l_returnflag") == "R").alias("returned"))
    counted = orders.select("o_orderkey").join(per_order, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    focus = F.col("o_orderkey").cast("string").alias("focus_id")
    placed = customer.select("c_custkey").join(orders.groupBy("o_custkey").agg(one.alias("n")), F.col("c_custkey") == F.col("o_custkey"), "left")
    dated = lines.select("l_orderkey", "l_linenumber", "l_shipdate").join(orders.select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    line_id = F.concat_ws("-", "l_orderkey", "l_linenumber").alias("focus_id")
    return {
        ("Order", "hasLineItem"): counted.select(focus, F.coalesce("n", F.lit(0)).cast("long").alias("observed")),
        ("Order", "hasReturnedLine"): counted.select(focus, F.coalesce("returned", F.lit(0)).cast("long").alias("observed")),
        ("Customer", "hasNegativeBalance"): customer.select(F.col("c_custkey").cast("string").alias("focus_id"), (F.col("c_acctbal") < 0).cast("long").alias("observed")),
        ("Customer", "placesOrder"): placed.select(F.col("c_custkey").cast("string").alias("focus_id"), F.coalesce("n", F.lit(0)).cast("long").alias("observed")),
        ("Supplier", "hasNegativeBalance"): supplier.select(F.col("s_suppkey").cast("string").alias("focus_id"), (F.col("s_acctbal") < 0).cast("long").alias("observed")),
        ("OrderSlot", "hasLine"): lines.groupBy("l_orderkey", "l_linenumber").agg(one.cast("long").alias("observed")).select(line_id, "observed"),
        ("LineItem", "shippedBeforeOrdered"): dated.select(line_id, (F.col("l_shipdate") < F.col("o_orderdate")).cast("long").alias("observed")),
        ("LineItem", "hasHighDiscount"): lines.select(line_id, (F.col("l_discount") > 0.09).cast("long").alias("observed")),
    }


def check_path(measured: DataFrame, constraints: list[Constraint]) -> DataFrame:
    """Violations of all constraints on one path, from one pass over its counts."""
    each = []
    for c in constraints:
        bad = F.lit(False)
        if c.min_count is not None:
            bad = bad | (F.col("observed") < c.min_count)
        if c.max_count is not None:
            bad = bad | (F.col("observed") > c.max_count)
        each.append(F.when(bad, F.struct(F.lit(c.shape).alias("shape_id"), F.lit(c.focus_class).alias("focus_class"), F.lit(c.path).alias("path"), F.lit(c.severity).alias("severity"))))
    hits = F.filter(F.array(*each), lambda x: x.isNotNull())
    return measured.select("focus_id", "observed", F.explode(hits).alias("v")).select("v.shape_id", "v.focus_class", "focus_id", "v.path", "observed", "v.severity")


def validate_tables(spark: SparkSession, sf_dir: str, constraints: tuple[Constraint, ...] = STAR) -> DataFrame:
    """``(shape_id, focus_class, focus_id, path, observed, severity)``; permissions never fail."""
    measured = paths(spark, sf_dir)
    grouped: dict[tuple[str, str], list[Constraint]] = {}
    for c in constraints:
        if (c.min_count, c.max_count) != (None, None):
            grouped.setdefault((c.focus_class, c.path), []).append(c)
    out = None
    for key, some in grouped.items():
        v = check_path(measured[key], some)
        out = v if out is None else out.unionByName(v)
    return out


def triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(s, p, o, otype)`` of customers, orders and line items, types included."""
    customer = table(spark, sf_dir, "customer", "c_custkey", "c_name", "c_acctbal", "c_mktsegment")
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderpriority")
    lines = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_returnflag")
    c_id = F.concat(F.lit("customer/"), F.col("c_custkey"))
    o_id = F.concat(F.lit("order/"), F.col("o_orderkey"))
    parts = [
        customer.select(c_id.alias("s"), F.lit("type").alias("p"), F.lit("Customer").alias("o"), F.lit("iri").alias("otype")),
        orders.select(o_id.alias("s"), F.lit("type").alias("p"), F.lit("Order").alias("o"), F.lit("iri").alias("otype")),
        customer.where("c_acctbal < 0").select(c_id.alias("s"), F.lit("hasNegativeBalance").alias("p"), F.lit("true").alias("o"), F.lit("boolean").alias("otype")),
        orders.select(F.concat(F.lit("customer/"), F.col("o_custkey")).alias("s"), F.lit("placesOrder").alias("p"), o_id.alias("o"), F.lit("iri").alias("otype")),
        lines.select(F.concat(F.lit("order/"), F.col("l_orderkey")).alias("s"), F.lit("hasLineItem").alias("p"), F.concat_ws("-", "l_orderkey", "l_linenumber").alias("o"), F.lit("iri").alias("otype")),
        lines.where("l_returnflag = 'R'").select(F.concat(F.lit("order/"), F.col("l_orderkey")).alias("s"), F.lit("hasReturnedLine").alias("p"), F.concat_ws("-", "l_orderkey", "l_linenumber").alias("o"), F.lit("iri").alias("otype")),
    ]
    attributes = customer.select(c_id.alias("s"), "c_name", "c_mktsegment").unpivot("s", ["c_name", "c_mktsegment"], "p", "o").withColumn("otype", F.lit("string"))
    out = attributes
    for p in parts:
        out = out.unionByName(p)
    return out


def star_triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``triples`` with suppliers, order slots, dates and discounts: the facts of every checkable shape.

    Lines that share an order and a number are nodes of their own; their last path step is what reports show.
    """
    supplier = table(spark, sf_dir, "supplier", "s_suppkey", "s_acctbal").withColumn("s", F.concat(F.lit("supplier/"), F.col("s_suppkey")))
    orders = table(spark, sf_dir, "orders", "o_orderkey", "o_orderdate")
    lines = table(spark, sf_dir, "lineitem")
    slot = F.concat_ws("-", "l_orderkey", "l_linenumber")
    nth = F.row_number().over(Window.partitionBy("l_orderkey", "l_linenumber").orderBy(*lines.columns))
    lines = lines.select("l_orderkey", "l_linenumber", "l_discount", "l_shipdate", F.concat(F.lit("line/"), nth, F.lit("/"), slot).alias("s"), F.concat(F.lit("slot/"), slot).alias("slot"))
    dated = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).where("l_shipdate < o_orderdate")

    def fact(df: DataFrame, s: str, p: str, o: Column, otype: str) -> DataFrame:
        return df.select(F.col(s).alias("s"), F.lit(p).alias("p"), o.alias("o"), F.lit(otype).alias("otype"))

    yes = F.lit("true")
    out = triples(spark, sf_dir)
    for part in (
        fact(supplier, "s", "type", F.lit("Supplier"), "iri"),
        fact(lines, "s", "type", F.lit("LineItem"), "iri"),
        fact(lines.select("slot").distinct(), "slot", "type", F.lit("OrderSlot"), "iri"),
        fact(supplier.where("s_acctbal < 0"), "s", "hasNegativeBalance", yes, "boolean"),
        fact(lines, "slot", "hasLine", F.col("s"), "iri"),
        fact(dated, "s", "shippedBeforeOrdered", yes, "boolean"),
        fact(lines.where("l_discount > 0.09"), "s", "hasHighDiscount", yes, "boolean"),
    ):
        out = out.unionByName(part)
    return out


def validate_triples(graph: DataFrame, constraints: tuple[Constraint, ...]) -> DataFrame:
    """The same report from triples: target class, focus nodes, path counts, comparison."""
    spark = graph.sparkSession
    spec = spark.createDataFrame([(c.shape, c.focus_class, c.path, c.min_count, c.max_count, c.severity) for c in constraints], "shape_id string, focus_class string, path string, min_count int, max_count int, severity string")
    spec = F.broadcast(spec)  # a row for each constraint
    focus = graph.where("p = 'type'").select(F.col("s"), F.col("o").alias("focus_class"))
    counts = graph.where(F.col("p").isin(*{c.path for c in constraints})).groupBy("s", "p").agg(F.count(F.lit(1)).alias("n"))
    targets = focus.join(spec, "focus_class")
    measured = targets.join(counts.withColumnRenamed("p", "path"), ["s", "path"], "left").withColumn("observed", F.coalesce("n", F.lit(0)).cast("long"))
    low = F.coalesce(F.col("observed") < F.col("min_count"), F.lit(False))
    high = F.coalesce(F.col("observed") > F.col("max_count"), F.lit(False))
    return measured.where(low | high).select("shape_id", "focus_class", F.substring_index("s", "/", -1).alias("focus_id"), "path", "observed", "severity")


def validate_shapes(spark: SparkSession, sf_dir: str, emitted: DataFrame) -> DataFrame:
    """Violations of emitted shapes on the measured (class, path) pairs; invalid shapes are skipped, permissions never fail.

    A qualified minimum counts the values of the path, which all have its one value class here.  The distinct
    constraints on measured pairs are a few dozen whatever the corpus: counts are 0 or 1, severities three.
    """
    measured = None
    for (cls, path), df in paths(spark, sf_dir).items():
        d = df.select(F.lit(cls).alias("focus_class"), F.lit(path).alias("path"), "focus_id", "observed")
        measured = d if measured is None else measured.unionByName(d)
    some = F.array(*[F.lit(f"{c}|{p}") for c, p in paths(spark, sf_dir)])
    spec = shapes.rules_only(shapes.load_valid(emitted)).where(F.array_contains(some, F.concat_ws("|", "target_class", "path")))
    spec = F.broadcast(spec.withColumnRenamed("target_class", "focus_class"))
    return measured.join(spec, ["focus_class", "path"]).where(violated(F.col("observed")))


def violated(observed: Column) -> Column:
    """Whether a count breaks ``min_count``, ``max_count`` or ``q_min`` of the same row."""
    low = observed < F.greatest(F.coalesce("min_count", F.lit(0)), F.coalesce("q_min", F.lit(0)))
    return low | F.coalesce(observed > F.col("max_count"), F.lit(False))


def planted_entities(emitted: DataFrame, gold: DataFrame) -> DataFrame:
    """``(sent_id, route, negative, flagged)``: two entities of the gold class for each obligation and prohibition.

    The positive one does what the gold rule asks, the negative one doesn't; ``flagged`` tells whether the sentence's
    own shape, run on the entity, reports it.  A shape on another class or path finds no value there, and one
    that isn't valid is never loaded.
    """
    j = shapes.with_validity(emitted).join(gold.where("gold_label in ('O', 'F')").select("sent_id", "gold_label", "gold_class", "gold_pred"), "sent_id")
    j = j.withColumn("negative", F.explode(F.array(F.lit(False), F.lit(True))))
    has = (F.col("gold_label") == "O") != F.col("negative")
    aimed = F.coalesce(F.col("target_class") == F.col("gold_class"), F.lit(False))
    seen = F.when(aimed & F.coalesce(F.col("path") == F.col("gold_pred"), F.lit(False)), has.cast("int")).otherwise(F.lit(0))
    return j.select("sent_id", "route", "negative", (F.col("valid") & aimed & violated(seen)).alias("flagged"))


def entity_report(violations: DataFrame) -> DataFrame:
    """For each focus node: how many violations, the worst severity, and the paths."""
    rank = F.when(F.col("severity") == "Violation", 3).when(F.col("severity") == "Warning", 2).otherwise(1)
    return violations.groupBy("focus_class", "focus_id").agg(F.count(F.lit(1)).alias("n"), F.max_by("severity", rank).alias("worst"), F.array_join(F.array_sort(F.collect_set("path")), ",").alias("paths"))
