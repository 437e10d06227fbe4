"""Arithmetic of score sheets: averages, wins, speed-ups, frontiers.

The sheet is made from all of ``lineitem``: a supplier is a benchmark, a line number a system, the mean quantity a score
and the mean price the seconds beyond a start of 1,000.
"""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..plans import reference_scores as R
from ..sources import adapters as A

CATEGORIES = ("video", "grounding", "spatial")


def _scores(spark, d):
    line = F.col("l_linenumber").cast("int")
    runs = A.table(spark, d, "lineitem").filter(line <= len(R.SYSTEMS)).withColumns({"system": F.element_at(F.array(*map(F.lit, R.SYSTEMS)), line), "cents": A.cents("l_extendedprice")})
    sheet = runs.groupBy(F.col("l_suppkey").cast("string").alias("benchmark"), F.element_at(F.array(*map(F.lit, CATEGORIES)), (F.col("l_suppkey") % 3 + 1).cast("int")).alias("category"), "system")
    return sheet.agg((F.sum(F.col("l_quantity").cast("long")) / F.count("*")).alias("value"), (1000 + F.sum("cents") / F.count("*") / 100).alias("time_s"))


def _selectors(spark, d):
    """Odd lines are runs with the first selector, even ones with the second; the discount in percent stands for canvases."""
    odd = F.col("l_linenumber") % 2 == 1
    mean = lambda when, v: F.try_divide(F.sum(F.when(when, v)).cast("double"), F.count_if(when))
    quantity, canvases = F.col("l_quantity").cast("long"), A.cents("l_discount") + 1
    cells = {"a": (odd, quantity), "a_canvas": (odd, canvases), "b": (~odd, quantity), "b_canvas": (~odd, canvases)}
    return A.table(spark, d, "lineitem").groupBy("l_suppkey").agg(*[mean(*c).alias(n) for n, c in cells.items()])


def reference_table_checks(spark, d):
    """Average score and canvases of the two selectors, and their ratio in percent."""
    s = _selectors(spark, d)
    return s.agg(*[F.round(F.avg(c), 6).alias(f"avg_{c}") for c in ("a", "a_canvas", "b", "b_canvas")], F.round(100 * F.avg("b_canvas") / F.avg("a_canvas"), 6).alias("canvas_percent"))


def category_averages(spark, d):
    s = _scores(spark, d)
    return s.groupBy("system", "category").agg(F.round(F.avg("value"), 6).alias("average"), F.count("*").alias("n"))


def average_of_averages(spark, d):
    return category_averages(spark, d).groupBy("system").agg(F.round(F.avg("average"), 6).alias("average"))


def wins_over_control(spark, d):
    s = _scores(spark, d)
    c = s.filter("system = 'control'").select("benchmark", F.col("value").alias("c"))
    return s.filter("system <> 'control'").join(c, "benchmark").groupBy("system").agg(F.count_if(F.col("value") > F.col("c")).alias("wins"), F.count("*").alias("n"))


def rank_marks(spark, d):
    """Best and second best of each benchmark."""
    w = Window.partitionBy("benchmark").orderBy(F.desc("value"))
    return _scores(spark, d).withColumn("rank", F.dense_rank().over(w)).filter("rank <= 2").select("benchmark", "system", "rank")


def speedup_reference(spark, d):
    """Seconds of the control over those of each operating point."""
    s = _scores(spark, d)
    c = s.filter("system = 'control'").select("benchmark", F.col("time_s").alias("c"))
    return s.filter("system like 'tc%'").join(c, "benchmark").select("benchmark", "system", F.round(F.col("c") / F.col("time_s"), 6).alias("speedup"))


def load_time_allowance(spark, d):
    """Rival's seconds less 1.01 s per eight samples, own system fully charged; 1,000 samples."""
    return _scores(spark, d).filter("system = 'large'").select("benchmark", F.round(F.col("time_s") - 1.01 * 1000 / 8, 6).alias("adjusted_s"))


def pareto_reference(spark, d):
    """Systems that none beats in both score and seconds, per benchmark (a left anti join on few rows)."""
    a, b = _scores(spark, d).alias("a"), _scores(spark, d).alias("b")
    better = F.expr("a.benchmark = b.benchmark and b.value >= a.value and b.time_s <= a.time_s and (b.value > a.value or b.time_s < a.time_s)")
    return a.join(b, better, "left_anti").select("benchmark", "system")


def delta_pivot(spark, d):
    """tc32 less tc8 and less the control."""
    p = _scores(spark, d).groupBy("benchmark").pivot("system", list(R.SYSTEMS)).agg(F.first("value"))
    return p.select("benchmark", F.round(F.col("tc32") - F.col("tc8"), 6).alias("over_tc8"), F.round(F.col("tc32") - F.col("control"), 6).alias("over_control"))


def knee_reference(spark, d):
    """Smallest operating point after which the mean score gains under one point."""
    m = _scores(spark, d).filter("system like 'tc%'").groupBy(F.substring("system", 3, 9).cast("int").alias("n")).agg(F.avg("value").alias("v"))
    w = Window.orderBy("n")  # three rows
    return m.withColumn("gain", F.lead("v").over(w) - F.col("v")).select("n", F.round("v", 6).alias("mean"), F.round("gain", 6).alias("gain"), (F.coalesce("gain", F.lit(0.0)) < 1).alias("flat"))


_F = (reference_table_checks, category_averages, average_of_averages, wins_over_control, rank_marks, speedup_reference, load_time_allowance, pareto_reference, delta_pivot, knee_reference)
QUERIES = {f.__name__: f for f in _F}
S = f"""s as (select l_suppkey::varchar benchmark, ({list(CATEGORIES)})[l_suppkey % 3 + 1] category, ({list(R.SYSTEMS)})[l_linenumber] "system",
  sum(l_quantity::bigint)::double / count(*) "value", 1000 + sum(round(l_extendedprice::double * 100)::bigint)::double / count(*) / 100 time_s from lineitem where l_linenumber <= {len(R.SYSTEMS)} group by 1, 2, 3)"""
X = """y as (select l_suppkey, l_linenumber % 2 = 1 odd, l_quantity::bigint q, round(l_discount::double * 100)::bigint + 1 k from lineitem),
x as (select l_suppkey, (sum(q) filter (odd))::double / nullif(count(*) filter (odd), 0) a, (sum(k) filter (odd))::double / nullif(count(*) filter (odd), 0) a_canvas,
  (sum(q) filter (not odd))::double / nullif(count(*) filter (not odd), 0) b, (sum(k) filter (not odd))::double / nullif(count(*) filter (not odd), 0) b_canvas from y group by 1)"""
SQL = {
    "reference_table_checks": f"with {X} select round(avg(a), 6) avg_a, round(avg(a_canvas), 6) avg_a_canvas, round(avg(b), 6) avg_b, round(avg(b_canvas), 6) avg_b_canvas, round(100 * avg(b_canvas) / avg(a_canvas), 6) canvas_percent from x",
    "category_averages": f'with {S} select "system", category, round(avg(value), 6) average, count(*) n from s group by 1, 2',
    "average_of_averages": f'with {S} select "system", round(avg(average), 6) average from (select "system", category, round(avg(value), 6) average from s group by 1, 2) group by 1',
    "wins_over_control": f"""with {S} select s."system", count(*) filter (s.value > c.value) wins, count(*) n from s join s c on c."system" = 'control' and c.benchmark = s.benchmark where s."system" <> 'control' group by 1""",
    "rank_marks": f'with {S} select benchmark, "system", r::int "rank" from (select *, dense_rank() over (partition by benchmark order by value desc) r from s) where r <= 2',
    "speedup_reference": f"""with {S} select s.benchmark, s."system", round(c.time_s / s.time_s, 6) speedup from s join s c on c."system" = 'control' and c.benchmark = s.benchmark where s."system" like 'tc%'""",
    "load_time_allowance": f"""with {S} select benchmark, round(time_s - 1.01::double * 1000 / 8, 6) adjusted_s from s where "system" = 'large'""",
    "pareto_reference": f"""with {S} select benchmark, "system" from s a where not exists (select 1 from s b where a.benchmark = b.benchmark and b.value >= a.value and b.time_s <= a.time_s and (b.value > a.value or b.time_s < a.time_s))""",
    "delta_pivot": f"""with {S} select benchmark, round(max(value) filter ("system" = 'tc32') - max(value) filter ("system" = 'tc8'), 6) over_tc8, round(max(value) filter ("system" = 'tc32') - max(value) filter ("system" = 'control'), 6) over_control from s group by 1""",
    "knee_reference": f"""with {S}, m as (select substr("system", 3)::int n, avg(value) v from s where "system" like 'tc%' group by 1), g as (select *, lead(v) over (order by n) - v gain from m) select n, round(v, 6) mean, round(gain, 6) gain, coalesce(gain, 0) < 1 flat from g""",
}
