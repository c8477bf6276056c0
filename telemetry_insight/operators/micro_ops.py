"""Queries about single events: surroundings, manoeuvres, shock places."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import analytics as A
from ..functions import geo
from ..functions import questions as Q
from ..plans.store import LABELLED_SQL, labelled_windows
from ..sources import carriers as C
from .registry import query

L = f"WITH {LABELLED_SQL}"


def surroundings(spark, d, event_id: int, radius_m: float = 100.0):
    """label, neighbours, mean instability around one event, which itself is left out."""
    w = labelled_windows(spark, d)
    at = w.where(F.col("event_id") == event_id).first()
    near = geo.within(w.where(F.col("event_id") != event_id), at["lat"], at["lon"], radius_m)
    return at, near.groupBy("label").agg(F.count(F.lit(1)).alias("neighbours"), F.avg("instability").alias("mean_instability"))


def context(spark, d, event_id: int) -> Q.Facts:
    at, near = surroundings(spark, d, event_id)
    rows = near.orderBy("label").collect()
    numbers = {f"{r['label']} nearby": r["neighbours"] for r in rows} | {"instability": round(at["instability"], 2)}
    return Q.Facts(f"Event of profile {at['label']}", numbers, [(at["place"], round(at["landmark_m"], 2))], at["label"])


def _micro(name: str, label: str):
    pick = f"(SELECT event_id FROM lw WHERE label = '{label}' ORDER BY extreme DESC, event_id LIMIT 1)"

    @query(name, f"{L}, c AS (SELECT * FROM lw WHERE event_id = {pick}) SELECT c.event_id AS event_id, c.place AS place, lw.label AS label, count(*) AS neighbours, round(avg(lw.instability), 6) AS mean_instability FROM lw, c WHERE lw.event_id <> c.event_id AND {C.haversine_sql('c', 'lw')} <= 100 GROUP BY 1, 2, 3")
    def run(spark, d):
        top = labelled_windows(spark, d).where(F.col("label") == label).orderBy(F.desc("extreme"), "event_id").select("event_id").first()
        if top is None:
            return spark.createDataFrame([], "event_id long, place string, label string, neighbours long, mean_instability double")
        at, near = surroundings(spark, d, top["event_id"])
        return near.select(F.lit(top["event_id"]).alias("event_id"), F.lit(at["place"]).alias("place"), "label", "neighbours", F.round("mean_instability", 6).alias("mean_instability"))

    return run


for _n, _l in (("sudden_braking", "Very Aggressive"), ("sharp_turn", "Slightly Unstable"), ("vertical_shocks", "Aggressive")):
    _micro(_n, _l)


@query("micro_context", f"{L}, c AS (SELECT * FROM lw WHERE event_id = 17) SELECT lw.label AS label, count(*) AS neighbours, round(avg(lw.instability), 6) AS mean_instability FROM lw, c WHERE lw.event_id <> 17 AND {C.haversine_sql('c', 'lw')} <= 100 GROUP BY 1")
def micro_context(spark, d):
    return surroundings(spark, d, 17)[1].withColumn("mean_instability", F.round("mean_instability", 6))


@query("micro_prompt")
def micro_prompt(spark, d):
    text = Q.prompt("event", Q.fact_block(context(spark, d, 17)), "Why did this event happen?")
    c = Q.Config.micro()
    return spark.createDataFrame([(text, Q.tokens(text), c.temperature, c.max_tokens)], "prompt string, tokens int, temperature double, max_tokens int")


@query("maneuver_type", f"{L} SELECT CASE WHEN x_p99 - x_p01 >= y_p99 - y_p01 AND x_p99 - x_p01 >= z_p99 - z_p01 THEN CASE WHEN round(abs(x_p01), 9) > round(abs(x_p99), 9) THEN 'braking' ELSE 'acceleration' END WHEN y_p99 - y_p01 >= z_p99 - z_p01 THEN 'turn' ELSE 'shock' END AS maneuver, label, count(*) AS windows FROM lw GROUP BY 1, 2")
def maneuver_type(spark, d):
    return labelled_windows(spark, d).groupBy(A.maneuver().alias("maneuver"), "label").agg(F.count(F.lit(1)).alias("windows"))


@query("shock_localization", f"{L}, g AS (SELECT CAST(floor(lat / 0.002) AS BIGINT) AS cy, CAST(floor(lon / 0.002) AS BIGINT) AS cx, count(*) AS n FROM lw WHERE label IN ('Aggressive', 'Very Aggressive') GROUP BY 1, 2) SELECT cy, cx, n AS shocks, round(sum(n) OVER (ORDER BY n DESC, cy, cx ROWS UNBOUNDED PRECEDING) / sum(n) OVER (), 6) AS cumulative_share FROM g")
def shock_localization(spark, d):
    """Cells of severe windows with the running share of the most affected first: a steep start means few bad places."""
    from pyspark.sql import Window

    g = labelled_windows(spark, d).where(F.col("label").isin(*A.SEVERE)).groupBy(geo.cell(F.col("lat")).alias("cy"), geo.cell(F.col("lon")).alias("cx")).agg(F.count(F.lit(1)).alias("shocks"))
    w = Window.orderBy(F.desc("shocks"), "cy", "cx").rowsBetween(Window.unboundedPreceding, 0)  # over the cells of the service area, a bounded grid
    return g.withColumn("cumulative_share", F.round(F.sum("shocks").over(w) / F.sum("shocks").over(Window.partitionBy()), 6))
