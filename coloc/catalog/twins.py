"""DuckDB SQL that stands beside the plans: common table expressions by name, put together on demand."""

from __future__ import annotations

import re

from coloc.functions.draws import draw_sql
from coloc.operators.grids import Grid

#: Simulations and features of an antecedent or pattern, as the experiments have them.
R, D = 99, 3


def _u(tag: str, key: str) -> str:
    return draw_sql(f"'{tag}'", f"({key})::VARCHAR")


def _us(tag: str, key: str) -> str:
    """A draw for a simulation."""
    return draw_sql(f"'{tag}'", "sim_id::VARCHAR", "':'", f"({key})::VARCHAR")


_CX, _CY = "(c_nationkey % 5) * 40.0", "floor(c_nationkey / 5) * 40.0"
CTES: dict[str, str] = {
    "facilities": f"SELECT s_suppkey::VARCHAR AS site_id, s_nationkey AS nation, (s_nationkey % 5) * 40.0 + 40.0 * {_u('x', 's_suppkey')} AS x, floor(s_nationkey / 5) * 40.0 + 40.0 * {_u('y', 's_suppkey')} AS y FROM supplier",
    "yearly": "SELECT l_suppkey, p_brand AS feature, year(l_shipdate) AS y, sum(l_quantity) AS q FROM lineitem JOIN part ON p_partkey = l_partkey GROUP BY ALL",
    "amounts": "SELECT l_suppkey::VARCHAR AS site_id, feature, avg(q) AS amount FROM yearly GROUP BY ALL",
    "top4": "SELECT site_id, feature, amount FROM amounts QUALIFY row_number() OVER (PARTITION BY site_id ORDER BY amount DESC, feature) <= 4",
    "common": "SELECT feature FROM top4 GROUP BY feature HAVING count(DISTINCT site_id) >= 3",
    "emissions": "SELECT site_id || '/' || feature AS object_id, feature, site_id, x, y, amount FROM top4 JOIN common USING (feature) JOIN facilities USING (site_id)",
    "cases0": "SELECT *, c_mktsegment IN ('BUILDING', 'HOUSEHOLD', 'AUTOMOBILE') AS urban FROM customer WHERE c_acctbal < 0",
    "cases": f"""SELECT c_custkey::VARCHAR AS object_id, 'CASE' AS feature, c_nationkey AS nation, urban,
        CASE WHEN urban THEN {_CX} + 15.0 + 10.0 * {_u('cx', 'c_custkey')} ELSE {_CX} + 40.0 * {_u('cx', 'c_custkey')} END AS x,
        CASE WHEN urban THEN {_CY} + 15.0 + 10.0 * {_u('cy', 'c_custkey')} ELSE {_CY} + 40.0 * {_u('cy', 'c_custkey')} END AS y FROM cases0""",
    "target": "SELECT feature FROM emissions GROUP BY feature ORDER BY count(DISTINCT site_id) DESC, feature LIMIT 1",
    "bought": "SELECT o_custkey, l_suppkey, sum(l_quantity) AS q FROM lineitem JOIN orders ON o_orderkey = l_orderkey GROUP BY ALL",
    "mains": "SELECT o_custkey::VARCHAR AS object_id, l_suppkey::VARCHAR AS site_id FROM bought QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY q DESC, l_suppkey) = 1",
    "linked": "SELECT object_id, e.x AS sx, e.y AS sy FROM mains JOIN (SELECT site_id, x, y FROM emissions JOIN target USING (feature)) e USING (site_id)",
    "cases_linked": f"""SELECT c.object_id, feature, nation, urban, coalesce(sx + 6.0 * {_u('lx', 'c.object_id')} - 3.0, x) AS x, coalesce(sy + 6.0 * {_u('ly', 'c.object_id')} - 3.0, y) AS y, sx IS NOT NULL AS linked
        FROM cases c LEFT JOIN linked l ON l.object_id = c.object_id""",
    "people": "SELECT c_nationkey, count(*) AS population FROM customer GROUP BY ALL",
    "zones": "SELECT n_nationkey AS zone_id, (n_nationkey % 5) * 40.0 + 15.0 AS x0, floor(n_nationkey / 5) * 40.0 + 15.0 AS y0, (n_nationkey % 5) * 40.0 + 25.0 AS x1, floor(n_nationkey / 5) * 40.0 + 25.0 AS y1, coalesce(population, 0) AS population FROM nation LEFT JOIN people ON c_nationkey = n_nationkey",
    "ev": "SELECT *, (props->>'$.k')::INTEGER AS k FROM events",
    "event_points": "SELECT event_id::VARCHAR AS object_id, event_type AS feature, user_id::VARCHAR AS site_id, value AS x, k::DOUBLE AS y FROM ev WHERE value < 100",
    "embedding_points": "SELECT vec_id::VARCHAR AS object_id, 'L' || label AS feature, 100.0 * embedding[1]::DOUBLE AS x, 100.0 * embedding[2]::DOUBLE AS y FROM embeddings WHERE embedding IS NOT NULL",
    "daily": "SELECT user_id AS station_id, ts::DATE AS day, value AS speed, k * 3.6 AS bearing FROM ev",
    "daily8": "SELECT *, (floor((bearing + 22.5) % 360.0 / 45))::INTEGER AS octant FROM daily",
    "modes": "SELECT station_id, octant FROM (SELECT station_id, octant, count(*) AS c FROM daily8 GROUP BY station_id, octant) QUALIFY row_number() OVER (PARTITION BY station_id ORDER BY c DESC, octant) = 1",
    "normals": "SELECT station_id, avg(speed) AS speed, count(*) AS n_obs, any_value(m.octant) AS octant, any_value(m.octant) * 45.0 AS bearing FROM daily8 JOIN modes m USING (station_id) GROUP BY station_id",
    "stations": f"SELECT *, 200.0 * {_u('wx', 'station_id')} AS x, 200.0 * {_u('wy', 'station_id')} AS y, speed * sin(radians(bearing)) AS u, speed * cos(radians(bearing)) AS v FROM normals",
    "sims": f"SELECT unnest(generate_series(1, {R}))::INTEGER AS sim_id",
    "paths": "SELECT user_id::VARCHAR AS object_id, 'PATH' AS feature, list({'x': value, 'y': k::DOUBLE} ORDER BY ts, event_id) AS ring FROM ev WHERE value < 100 GROUP BY user_id",
    "squares": "SELECT zone_id::VARCHAR AS object_id, r_name AS feature, x0, y0, x1, y1 FROM zones JOIN nation ON n_nationkey = zone_id JOIN region ON r_regionkey = n_regionkey",
    "baskets": "SELECT l_orderkey AS tx_id, p_type AS item, l_quantity / 50.0 AS p FROM lineitem JOIN part ON p_partkey = l_partkey",
    # simulations
    "em_slots": "SELECT sim_id, row_number() OVER (PARTITION BY sim_id ORDER BY site_id, feature) AS slot, site_id, x, y, amount AS site_amount FROM emissions, sims",
    "em_drawn": "SELECT sim_id, row_number() OVER (PARTITION BY sim_id ORDER BY md5('p' || sim_id || ':' || site_id || feature), site_id, feature) AS slot, feature, amount FROM emissions, sims",
    "rand_causes": "SELECT sim_id, site_id || '/' || slot AS object_id, site_id, x, y, feature, amount, site_amount FROM em_slots JOIN em_drawn USING (sim_id, slot)",
}


def rand_cases(source: str) -> dict[str, str]:
    s = source
    return {
        f"{s}_urban": f"SELECT *, row_number() OVER (ORDER BY object_id) AS k FROM {s} WHERE urban",
        f"{s}_quota": f"SELECT zones.*, total, total * population / (sum(population) OVER ()) AS quota FROM zones, (SELECT count(*) AS total FROM {s}_urban) AS n",
        f"{s}_share": f"SELECT *, floor(quota) + CASE WHEN row_number() OVER (ORDER BY quota - floor(quota) DESC, zone_id) <= total - sum(floor(quota)) OVER () THEN 1 ELSE 0 END AS share FROM {s}_quota",
        f"{s}_cum": f"SELECT *, sum(share) OVER (ORDER BY zone_id ROWS UNBOUNDED PRECEDING) AS high, high - share AS low FROM {s}_share",
        f"{s}_inner": f"SELECT sim_id, object_id, feature, true AS urban, x0 + (x1 - x0) * {_us('sx', 'object_id')} AS x, y0 + (y1 - y0) * {_us('sy', 'object_id')} AS y FROM (SELECT object_id, feature, k FROM {s}_urban) c JOIN {s}_cum ON k > low AND k <= high, sims",
        f"{s}_tries": f"SELECT sim_id, object_id, feature, t, 200.0 * {draw_sql(chr(39) + 'rx' + chr(39), 'sim_id::VARCHAR', chr(39) + ':' + chr(39), 't::VARCHAR', chr(39) + ':' + chr(39), 'object_id')} AS x, 200.0 * {draw_sql(chr(39) + 'ry' + chr(39), 'sim_id::VARCHAR', chr(39) + ':' + chr(39), 't::VARCHAR', chr(39) + ':' + chr(39), 'object_id')} AS y FROM (SELECT object_id, feature FROM {s} WHERE NOT urban), sims, (SELECT unnest(generate_series(0, 7)) AS t)",
        f"{s}_outer": f"SELECT sim_id, object_id, feature, false AS urban, x, y FROM {s}_tries q QUALIFY row_number() OVER (PARTITION BY sim_id, object_id ORDER BY CASE WHEN EXISTS (SELECT 1 FROM zones z WHERE q.x >= z.x0 AND q.x < z.x1 AND q.y >= z.y0 AND q.y < z.y1) THEN 100 - t ELSE t END) = 1",
        f"rand_{s}": f"SELECT * FROM {s}_inner UNION ALL SELECT * FROM {s}_outer",
    }


CTES |= rand_cases("cases_linked") | rand_cases("cases")
CIRCLE = "r AS a, r AS b, x AS cx, y AS cy, 1.0 AS ux, 0.0 AS uy"


def sql(final: str, **own: str) -> str:
    """final with the expressions it needs, its own first choice."""
    known = CTES | own
    order: list[str] = []

    def need(text: str) -> None:
        for name in dict.fromkeys(re.findall(r"\b[a-z_][a-z0-9_]*\b", text)):
            if name in known and name not in order and name not in busy:
                busy.add(name)
                need(known[name])
                order.append(name)

    busy: set[str] = set()
    need(final)
    if not order:
        return final
    return "WITH " + ",\n".join(f"{n} AS ({known[n]})" for n in order) + "\n" + final


DECAY_SQL = {
    "cosine": "cos(pi() * least(1.0, d / dm)) / 2.0 + 0.5",
    "linear": "1.0 - least(1.0, d / dm)",
    "steps": "CASE WHEN d > dm THEN 0.0 ELSE coalesce([1.0, 0.75, 0.5, 0.25][floor(d / 2.0)::INTEGER + 1], 0.0) END",
    "boolean": "1.0",
    "custom": "greatest(0.0, least(1.0, exp(-d)))",
}


def tx_ctes(source: str, grid: Grid, decay: str = "cosine", dmax: str = "ray", by: tuple[str, ...] = (), name: str = "tx", noisy: bool = False) -> dict[str, str]:
    """name and its steps: transactions of a buffered source (feature, x, y, r and the ellipse's columns)."""
    i0, i1, j0, j1 = grid.bounds
    h, k = grid.step, "".join(f"{b}, " for b in by)
    wx, wy = "sqrt(a * a * ux * ux + b * b * uy * uy)", "sqrt(a * a * uy * uy + b * b * ux * ux)"
    reach = {
        "ray": "CASE WHEN a = b AND cx = x AND cy = y THEN r WHEN d = 0 THEN 1.0 ELSE (sqrt(greatest(q * q - 4 * p2 * r2, 0.0)) - q) / (2 * p2) END",
        "major": "a + sqrt((cx - x) * (cx - x) + (cy - y) * (cy - y))",
        "radius": "r",
    }[dmax]
    p = f"1 - exp(sum(ln(1 - least(p, 1 - 1e-15))))" if noisy else "max(p)"
    return {
        f"{name}_b": f"SELECT *, greatest(ceil((cx - {wx} - {grid.dx}) / {h} - 1e-9), {i0})::BIGINT AS i0, least(floor((cx + {wx} - {grid.dx}) / {h} + 1e-9), {i1})::BIGINT AS i1, greatest(ceil((cy - {wy} - {grid.dy}) / {h} - 1e-9), {j0})::BIGINT AS j0, least(floor((cy + {wy} - {grid.dy}) / {h} + 1e-9), {j1})::BIGINT AS j1 FROM {source}",
        f"{name}_i": f"SELECT *, unnest(generate_series(i0, i1)) AS gi FROM {name}_b WHERE i0 <= i1 AND j0 <= j1",
        f"{name}_c": f"SELECT *, gi * {h} + {grid.dx} AS gx, gj * {h} + {grid.dy} AS gy FROM (SELECT *, unnest(generate_series(j0, j1)) AS gj FROM {name}_i)",
        f"{name}_d": f"SELECT *, sqrt((gx - x) * (gx - x) + (gy - y) * (gy - y)) AS d FROM {name}_c WHERE power((gx - cx) * ux + (gy - cy) * uy, 2) / (a * a) + power((gy - cy) * ux - (gx - cx) * uy, 2) / (b * b) <= 1 + 1e-12",
        f"{name}_e": f"SELECT *, CASE WHEN d > 0 THEN ((gx - x) * ux + (gy - y) * uy) / d ELSE 0 END AS e1, CASE WHEN d > 0 THEN ((gy - y) * ux - (gx - x) * uy) / d ELSE 0 END AS e2, (x - cx) * ux + (y - cy) * uy AS s FROM {name}_d",
        f"{name}_f": f"SELECT *, e1 * e1 / (a * a) + e2 * e2 / (b * b) AS p2, 2 * s * e1 / (a * a) AS q, s * s / (a * a) - 1 AS r2 FROM {name}_e",
        f"{name}_g": f"SELECT *, {reach} AS dm FROM {name}_f",
        f"{name}_p": f"SELECT *, greatest(0.0, least(1.0, {DECAY_SQL[decay]})) AS p FROM {name}_g",
        name: f"SELECT {k}gi, gj, feature, count(*)::INTEGER AS n_inst, ({p})::DECIMAL(18,12) AS p FROM {name}_p GROUP BY ALL",
    }


def pattern_ctes(tx: str = "tx", by: tuple[str, ...] = (), d: int = 2, name: str = "pats", on: str = "gi, gj") -> dict[str, str]:
    """name: key, size, sup, exp_sup of sets of up to d features."""
    k = "".join(f"{b}, " for b in by)
    using = f"{k}{on}"
    x = f"SELECT {k}{on}, feature AS last, feature AS key, p::DOUBLE AS p, 1 AS size FROM {tx}"
    out = {f"{name}1": x}
    for n in range(2, d + 1):
        out[f"{name}{n}"] = f"SELECT {using}, t.feature AS last, x.key || '+' || t.feature AS key, x.p * t.p::DOUBLE AS p, {n} AS size FROM {name}{n - 1} x JOIN {tx} t USING ({using}) WHERE t.feature > x.last"
    union = " UNION ALL ".join(f"SELECT {k}key, size, p FROM {name}{n}" for n in range(1, d + 1))
    out[name] = f"SELECT {k}key, size, count(*) AS sup, sum(p::DECIMAL(18,12)) AS exp_sup FROM ({union}) GROUP BY ALL"
    return out


def rule_ctes(tx: str = "tx", effect: str = "CASE", by: tuple[str, ...] = (), d: int = 3, name: str = "rules", on: str = "gi, gj") -> dict[str, str]:
    """name: key, size, sup, sup_lhs, exp_sup, exp_sup_lhs, conf, exp_conf of rules to the effect."""
    k = "".join(f"{b}, " for b in by)
    using = f"{k}{on}"
    out = {f"{name}_c": f"SELECT * FROM {tx} WHERE feature <> '{effect}'", f"{name}_e": f"SELECT {using}, p::DOUBLE AS pe FROM {tx} WHERE feature = '{effect}'"}
    out[f"{name}1"] = f"SELECT {using}, feature AS last, feature AS key, p::DOUBLE AS p, 1 AS size FROM {name}_c"
    for n in range(2, d + 1):
        out[f"{name}{n}"] = f"SELECT {using}, t.feature AS last, x.key || '+' || t.feature AS key, x.p * t.p::DOUBLE AS p, {n} AS size FROM {name}{n - 1} x JOIN {name}_c t USING ({using}) WHERE t.feature > x.last"
    union = " UNION ALL ".join(f"SELECT {using}, key, size, p FROM {name}{n}" for n in range(1, d + 1))
    out[f"{name}_s"] = f"SELECT {k}key, size, count(pe) AS sup, count(*) AS sup_lhs, sum((p * coalesce(pe, 0.0))::DECIMAL(18,12)) AS exp_sup, sum(p::DECIMAL(18,12)) AS exp_sup_lhs FROM ({union}) LEFT JOIN {name}_e USING ({using}) GROUP BY ALL"
    out[name] = f"SELECT *, CASE WHEN sup_lhs > 0 THEN sup::DOUBLE / sup_lhs END AS conf, CASE WHEN exp_sup_lhs > 0 THEN exp_sup::DOUBLE / exp_sup_lhs::DOUBLE END AS exp_conf FROM {name}_s"
    return out


def survivors(obs: str, sim: str, measure: str, support: str, most: int, extra: str = "") -> dict[str, str]:
    """found: keys with their exceedances, of those that exceed at most `most` times."""
    return {
        "exceeding": f"SELECT o.key, count(*) AS n FROM {obs} o JOIN {sim} s ON s.key = o.key AND s.{measure} >= o.{measure} GROUP BY o.key",
        "tested": f"SELECT o.*, coalesce(n, 0)::INTEGER AS exceed FROM {obs} o LEFT JOIN exceeding x ON x.key = o.key WHERE o.{support} > 0 {extra}",
        "found": f"SELECT * FROM tested WHERE exceed <= {most}",
    }
