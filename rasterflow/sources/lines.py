"""Plans from the given lines of orders: nets, renditions and accuracies that are counted in `lineitem`, not printed.

A line is an item.  It comes in the rendition of its return flag and goes to the net of its line number.  Preparing it
takes a time by its quantity and its rendition's size, running the net a time by the net's depth and the quantity's last
digit; rates are lines an hour.  A net is right where it closes a line (status F); an open line goes to the next net.
Sums are of whole numbers, so no figure depends on the order of the rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..plans import select
from ..registry import table

#: Time units (half a tenth of a second) in an hour.
HOUR = 72000.0


def cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows (model_id, stage, format_id, n, prep, work, closed): lines of each net and rendition, their time units and those closed."""
    flag, q = F.col("l_returnflag"), F.col("l_quantity")
    size = F.when(flag == "N", 6).when(flag == "R", 2).otherwise(1)
    form = F.when(flag == "N", "full").when(flag == "R", "half").otherwise("quarter")
    rows = table(spark, sf_dir, "lineitem").select(F.concat(F.lit("net"), "l_linenumber").alias("model_id"), F.col("l_linenumber").alias("stage"), form.alias("format_id"), (q * size).alias("prep"), (2 * F.col("l_linenumber") * (q % 10 + 1)).alias("work"), F.when(F.col("l_linestatus") == "F", 1).otherwise(0).alias("closed"))
    return rows.groupBy("model_id", "stage", "format_id").agg(F.count("*").alias("n"), F.sum("prep").alias("prep"), F.sum("work").alias("work"), F.sum("closed").alias("closed"))


def rate(n: str, units: str):
    return F.lit(HOUR) * F.sum(n) / F.nullif(F.sum(units), F.lit(0.0))


def candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows (model_id, exec, format_id, pre) of every net with every rendition."""
    c = cells(spark, sf_dir)
    nets = c.groupBy("model_id").agg(rate("n", "work").alias("exec"))
    return select.candidates(nets, c.groupBy("format_id").agg(rate("n", "prep").alias("pre")))


def plans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The candidates of which there are lines, with (plan_id, acc); acc in percent."""
    acc = cells(spark, sf_dir).select("model_id", "format_id", (F.lit(100.0) * F.col("closed") / F.col("n")).alias("acc"))
    return candidates(spark, sf_dir).join(F.broadcast(acc), ["model_id", "format_id"]).withColumn("plan_id", F.concat_ws("/", "model_id", "format_id"))


def cascades(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows (plan_id, stage, rate, pass_rate): for each rendition the nets in order, and the share of lines that each leaves open."""
    c = cells(spark, sf_dir).groupBy(F.col("format_id").alias("plan_id"), "stage")
    return c.agg(rate("n", "work").alias("rate"), (F.lit(1.0) * (F.sum("n") - F.sum("closed")) / F.sum("n")).alias("pass_rate"))


# The same in SQL.
CELLS = """(SELECT 'net' || l_linenumber AS model_id, l_linenumber AS stage, CASE l_returnflag WHEN 'N' THEN 'full' WHEN 'R' THEN 'half' ELSE 'quarter' END AS format_id, count(*) AS n,
 sum(l_quantity * CASE l_returnflag WHEN 'N' THEN 6 WHEN 'R' THEN 2 ELSE 1 END) AS prep, sum(2 * l_linenumber * (l_quantity % 10 + 1)) AS work, sum((l_linestatus = 'F')::INT) AS closed FROM lineitem GROUP BY 1, 2, 3)"""
CANDIDATES = f"""(SELECT model_id, exec, format_id, pre FROM (SELECT model_id, 72000.0::DOUBLE * sum(n) / nullif(sum(work), 0) AS exec FROM {CELLS} GROUP BY 1)
 CROSS JOIN (SELECT format_id, 72000.0::DOUBLE * sum(n) / nullif(sum(prep), 0) AS pre FROM {CELLS} GROUP BY 1))"""
PLANS = f"(SELECT model_id || '/' || format_id AS plan_id, *, least(pre, exec) AS est_tput FROM {CANDIDATES} JOIN (SELECT model_id, format_id, 100.0::DOUBLE * closed / n AS acc FROM {CELLS}) USING (model_id, format_id))"
CASCADES = f"(SELECT format_id AS plan_id, stage, 72000.0::DOUBLE * sum(n) / nullif(sum(work), 0) AS rate, 1.0::DOUBLE * (sum(n) - sum(closed)) / sum(n) AS pass_rate FROM {CELLS} GROUP BY 1, 2)"
