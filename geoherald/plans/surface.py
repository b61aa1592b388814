"""The SQL surface, and operators around the methods: views, functions, set operations, sketches, formats."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geoherald.functions.geometry import Grid
from geoherald.operators import matching
from geoherald.operators.assignment import Assignment
from geoherald.plans.oracles import AXIS, match
from geoherald.sources.shared import settle, shared_folder
from geoherald.sources.tables import read_table, round_trip
from geoherald.sources.workload import subscriptions
from geoherald.sources.world import WIDE_SIDE, wide_objects


def register_views(objects: DataFrame, subs: DataFrame, assignment: Assignment) -> dict[str, DataFrame]:
    """Temporary views ``objects, subscriptions, routing, matches`` over one run, and the functions below."""
    parts = matching.run(objects, subs, assignment)
    views = {"objects": objects, "subscriptions": subs, "routing": parts["live"], "matches": parts["matches"]}
    for name, df in views.items():
        df.createOrReplaceTempView(name)
    register_functions(objects.sparkSession)
    return views


def register_functions(spark: SparkSession) -> None:
    """``inside`` and ``satisfies`` in SQL; their bodies are inlined into the plan."""
    spark.sql("""create or replace temporary function inside(x bigint, y bigint, x0 bigint, y0 bigint, x1 bigint, y1 bigint)
        returns boolean return x between x0 and x1 and y between y0 and y1""")
    spark.sql("""create or replace temporary function satisfies(terms array<string>, dnf array<array<string>>)
        returns boolean return exists(dnf, clause -> forall(clause, t -> array_contains(terms, t)))""")


def cells_function(grid: Grid):
    """A table function of the cells under a rectangle, for SQL; plans here use ``Grid.overlapped``."""
    n, side = grid.n, grid.cell_side

    class CellsOf:
        def eval(self, x0: int, y0: int, x1: int, y1: int) -> Iterator[tuple[int]]:
            axis = lambda v: min(max(v // side, 0), n - 1)
            for cy in range(axis(y0), axis(y1) + 1):
                for cx in range(axis(x0), axis(x1) + 1):
                    yield (cy * n + cx,)

    return F.udtf(CellsOf, returnType="cell int")


def sql_matches(spark: SparkSession, folder: str) -> DataFrame:
    """Matches of all subscriptions, in SQL over the views: postings and probes meet on cell and term."""
    register_functions(spark)
    objects = settle(wide_objects(spark, folder), "objects")
    objects.createOrReplaceTempView("objects_v")
    settle(subscriptions(spark, folder, "Q1", objects=objects), "subs").createOrReplaceTempView("subs_v")
    return spark.sql("""
        with axes as (
          select sub_id, dnf, x0, y0, x1, y1, array_distinct(transform(dnf, c -> c[0])) as firsts,
            sequence(greatest(x0 div 65536, 0), least(x1 div 65536, 63)) as columns, sequence(greatest(y0 div 65536, 0), least(y1 div 65536, 63)) as rows
          from subs_v),
        postings as (
          select sub_id, dnf, x0, y0, x1, y1, cy * 64 + cx as cell, term
          from axes lateral view explode(firsts) as term lateral view explode(columns) as cx lateral view explode(rows) as cy),
        probes as (select obj_id, x, y, (y div 65536) * 64 + x div 65536 as cell, term from objects_v lateral view explode(terms) as term),
        near as (
          select distinct p.sub_id, o.obj_id, p.dnf from probes o join postings p using (cell, term)
          where inside(o.x, o.y, p.x0, p.y0, p.x1, p.y1))
        select n.sub_id, n.obj_id from near n join objects_v o using (obj_id) where satisfies(o.terms, n.dnf)""")


def set_difference(spark: SparkSession, folder: str) -> DataFrame:
    """Cities with objects but no customers of the building segment, by set operations."""
    homes = read_table(spark, folder, "customer")
    active = read_table(spark, folder, "events").join(homes, F.col("user_id") == F.col("c_custkey")).select("c_nationkey")
    return active.subtract(homes.filter("c_mktsegment = 'BUILDING' and c_acctbal > 9000").select("c_nationkey")).union(active.intersect(homes.filter("c_acctbal < 0").select("c_nationkey")))


def lateral_latest(spark: SparkSession, folder: str) -> DataFrame:
    """For each nation its three richest customers, by a lateral join that becomes a window."""
    nation, customer = read_table(spark, folder, "nation"), read_table(spark, folder, "customer")
    nation.createOrReplaceTempView("nation_v")
    customer.createOrReplaceTempView("customer_v")
    return spark.sql("""
        select n.n_nationkey, c.c_custkey from nation_v n,
        lateral (select c_custkey from customer_v where c_nationkey = n.n_nationkey order by c_acctbal desc, c_custkey limit 3) c""")


def union_sizes(spark: SparkSession, folder: str) -> DataFrame:
    """Distinct users per type of event and over all."""
    users = read_table(spark, folder, "events")
    each = users.groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))
    return each.union(users.agg(F.lit("all").alias("event_type"), F.countDistinct("user_id").alias("users")))


def union_sketches(spark: SparkSession, folder: str) -> DataFrame:
    """As :func:`union_sizes`, estimated by sketches that can be united without the rows: within a few hundredths."""
    users = read_table(spark, folder, "events")
    sketches = users.groupBy("event_type").agg(F.expr("theta_sketch_agg(user_id)").alias("s"))
    each = sketches.select("event_type", F.expr("theta_sketch_estimate(s)").cast("long").alias("users"))
    whole = sketches.agg(F.expr("theta_union_agg(s)").alias("s")).select(F.lit("all").alias("event_type"), F.expr("theta_sketch_estimate(s)").cast("long").alias("users"))
    return each.union(whole)


def formats(spark: SparkSession, folder: str) -> DataFrame:
    """Nations through csv, json and parquet and back."""
    nation = read_table(spark, folder, "nation")
    out = None
    for fmt in ("csv", "json", "parquet"):
        back = round_trip(nation, f"{shared_folder(spark)}/formats-{uuid.uuid4().hex}", fmt).withColumn("fmt", F.lit(fmt))
        out = back if out is None else out.union(back)
    return out


def cells_by_function(spark: SparkSession, folder: str) -> DataFrame:
    """Cells under a square around each of the first customers, by the table function."""
    spark.udtf.register("cells_of", cells_function(Grid(WIDE_SIDE, 6)))
    read_table(spark, folder, "customer").select("c_custkey", (F.col("c_custkey") * 48271 % WIDE_SIDE).alias("x"), (F.col("c_custkey") * 69621 % WIDE_SIDE).alias("y")).createOrReplaceTempView("spots_v")
    return spark.sql("select c_custkey, cell from spots_v, lateral cells_of(x - 50000, y - 50000, x + 50000, y + 50000)")


def medians(spark: SparkSession, folder: str) -> DataFrame:
    """Median and spread of places per nation, exactly."""
    homes = read_table(spark, folder, "customer").select(F.col("c_custkey"), "c_nationkey")
    rows = read_table(spark, folder, "events").join(homes, F.col("user_id") == F.col("c_custkey"))
    cents = F.round(F.col("value") * 100).cast("long")
    return rows.groupBy("c_nationkey").agg(F.percentile(cents, F.lit(0.5)).alias("median"), F.min(cents).alias("low"), F.max_by("event_id", F.struct(cents, "event_id")).alias("top_event"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "sql_matches": sql_matches,
        "set_difference": set_difference,
        "lateral_latest": lateral_latest,
        "union_sizes": union_sizes,
        "union_sketches": union_sketches,
        "formats": formats,
        "cells_by_function": cells_by_function,
        "medians": medians,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "sql_matches": match("Q1"),
        "set_difference": """with active as (select distinct c_nationkey from events join customer on user_id = c_custkey)
select c_nationkey from active where c_nationkey not in (select c_nationkey from customer where c_mktsegment = 'BUILDING' and c_acctbal > 9000)
union all select c_nationkey from active where c_nationkey in (select c_nationkey from customer where c_acctbal < 0)""",
        "lateral_latest": "select c_nationkey as n_nationkey, c_custkey from (select *, row_number() over (partition by c_nationkey order by c_acctbal desc, c_custkey) as r from customer join nation on c_nationkey = n_nationkey) where r <= 3",
        "union_sizes": "select event_type, count(distinct user_id) as users from events group by event_type union all select 'all', count(distinct user_id) from events",
        "formats": "select n_nationkey, n_name, n_regionkey, fmt from nation, (values ('csv'), ('json'), ('parquet')) f(fmt)",
        "cells_by_function": f"""with s as (select c_custkey, (c_custkey * 48271) % 4194304 - 50000 as x0, (c_custkey * 48271) % 4194304 + 50000 as x1, (c_custkey * 69621) % 4194304 - 50000 as y0, (c_custkey * 69621) % 4194304 + 50000 as y1 from customer),
c as (select *, unnest(range({AXIS.format(v="x0")}, {AXIS.format(v="x1")} + 1)) as cx from s)
select c_custkey, (cx + 64 * unnest(range({AXIS.format(v="y0")}, {AXIS.format(v="y1")} + 1)))::int as cell from c""",
        "medians": """select c_nationkey, quantile_cont(c, 0.5)::double as median, min(c) as low, arg_max(event_id, {'a': c, 'b': event_id}) as top_event
from (select *, round(value * 100)::bigint as c from events join customer on user_id = c_custkey) group by c_nationkey""",
    }
