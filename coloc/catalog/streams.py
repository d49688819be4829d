"""Streaming queries drained over the given events, with batch SQL twins."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coloc.catalog.registry import add, q4
from coloc.catalog.twins import sql
from coloc.sources.staging import shared_folder
from coloc.streaming import stateful, windows


def _run(s: SparkSession, d: str, build, mode: str) -> DataFrame:
    name = f"stream_{uuid.uuid4().hex}"
    return windows.drained(build(windows.points(windows.source(s, d))), mode, f"{shared_folder(s)}/{name}")


P = {"sp": "SELECT ts, event_id, user_id, event_type AS feature, round(value)::BIGINT AS gi, k::BIGINT AS gj, cos(pi() * abs(value - round(value))) / 2 + 0.5 AS p FROM ev WHERE value < 100"}
_iso = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss").alias("start")
add("stream_tumbling", lambda s, d: _run(s, d, windows.tumbling, "complete").groupBy(_iso("w.start"), "feature").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("p"), 4).alias("exp_sup")), sql(f"SELECT strftime(day, '%Y-%m-%d %H:%M:%S') AS start, feature, count(*) AS n, {q4('sum(p)', 'exp_sup')} FROM (SELECT date_trunc('day', ts) AS day, gi, gj, feature, max(p) AS p FROM sp GROUP BY ALL) GROUP BY ALL", **P))
add("stream_sliding", lambda s, d: _run(s, d, windows.sliding, "complete").select(_iso("w.start"), "feature", "n", F.round("sum_p", 4).alias("sum_p")), sql(f"SELECT strftime(date_trunc('day', ts) - to_days(k::INTEGER), '%Y-%m-%d %H:%M:%S') AS start, feature, count(*) AS n, {q4('sum(p)', 'sum_p')} FROM sp, (SELECT unnest(generate_series(0, 6)) AS k) GROUP BY ALL", **P))
add("stream_session", lambda s, d: _run(s, d, windows.sessions, "complete").select("user_id", _iso("w.start"), "n"), sql("SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS b FROM sp)) GROUP BY user_id, g", **P))


def static_join(s, d):
    radii = s.createDataFrame([("click", 1.0), ("view", 2.0), ("purchase", 3.0)], "feature string, r double")
    return _run(s, d, lambda pts: windows.with_radii(pts, radii).groupBy("feature").agg(F.count(F.lit(1)).alias("n"), F.max("r").alias("r")), "complete")


add("stream_static", static_join, sql("SELECT feature, count(*) AS n, max(r) AS r FROM sp JOIN (VALUES ('click', 1.0::DOUBLE), ('view', 2.0), ('purchase', 3.0)) AS t(feature, r) USING (feature) GROUP BY feature", **P))
add("stream_interval_pairs", lambda s, d: _run(s, d, lambda pts: windows.close_pairs(pts, "error", "purchase"), "append"), sql("SELECT a.event_id AS a, b.event_id AS b FROM sp a JOIN sp b USING (user_id) WHERE a.feature = 'error' AND b.feature = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR", **P))
add("stream_dedup", lambda s, d: _run(s, d, windows.deduplicated, "append").groupBy("feature").agg(F.count(F.lit(1)).alias("n")), sql("SELECT feature, count(DISTINCT event_id) AS n FROM sp GROUP BY feature", **P))
add("stream_running_supports", lambda s, d: _run(s, d, stateful.running_supports, "append").groupBy("key").agg(F.round(F.sum("delta"), 4).alias("exp_sup")).where("exp_sup > 0"), sql(f"SELECT * FROM (SELECT feature AS key, {q4('sum(p)', 'exp_sup')} FROM m GROUP BY feature UNION ALL SELECT a.feature || '+' || b.feature, {q4('sum(a.p * b.p)', 'exp_sup')} FROM m a JOIN m b USING (gi, gj) WHERE a.feature < b.feature GROUP BY ALL UNION ALL SELECT a.feature || '+' || b.feature || '+' || c.feature, {q4('sum(a.p * b.p * c.p)', 'exp_sup')} FROM m a JOIN m b USING (gi, gj) JOIN m c USING (gi, gj) WHERE a.feature < b.feature AND b.feature < c.feature GROUP BY ALL) WHERE exp_sup > 0", m="SELECT gi, gj, feature, max(p) AS p FROM sp GROUP BY ALL", **P))
