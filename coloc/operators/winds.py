"""Station normals and their interpolation to objects."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coloc.functions import angles
from coloc.operators import plates

#: Stations whose spline is solved as one dense system, at most; those of more by iteration (plates.py).
MAX_STATIONS = 4000


def normals(daily: DataFrame, min_obs: int = 1) -> DataFrame:
    """station_id, speed (mean), octant (most frequent, ties to the lowest), bearing, n_obs from daily speed and bearing."""
    rows = daily.withColumn("octant", angles.octant(F.col("bearing")))
    mean = rows.groupBy("station_id").agg(F.avg("speed").alias("speed"), F.count(F.lit(1)).alias("n_obs")).where(F.col("n_obs") >= min_obs)
    by = rows.groupBy("station_id", "octant").agg(F.count(F.lit(1)).alias("c"))
    order = W.partitionBy("station_id").orderBy(F.desc("c"), "octant")
    mode = by.withColumn("k", F.row_number().over(order)).where("k = 1").select("station_id", "octant")
    return mean.join(mode, "station_id").withColumn("bearing", F.col("octant") * 45.0)


def with_components(stations: DataFrame) -> DataFrame:
    u, v = angles.components(F.col("speed"), F.col("bearing"))
    return stations.withColumns({"u": u, "v": v})


def recomposed(rows: DataFrame) -> DataFrame:
    """speed and bearing of interpolated u, v."""
    return rows.withColumns({"speed": angles.speed(F.col("u"), F.col("v")), "bearing": angles.bearing(F.col("u"), F.col("v"))})


def idw(objects: DataFrame, stations: DataFrame, power: float = 2.0) -> DataFrame:
    """Inverse-distance weights over all stations (a bounded table, sent to all executors); a station at the very place wins."""
    st = stations.select(F.col("x").alias("sx"), F.col("y").alias("sy"), "u", "v")
    near = objects.select("object_id", "x", "y").distinct().crossJoin(F.broadcast(st)).withColumn("d", F.greatest(F.hypot(F.col("x") - F.col("sx"), F.col("y") - F.col("sy")), F.lit(1e-9)))
    w = F.pow("d", F.lit(-float(power)))
    got = near.groupBy("object_id").agg((F.sum(w * F.col("u")) / F.sum(w)).alias("u"), (F.sum(w * F.col("v")) / F.sum(w)).alias("v"))
    return recomposed(objects.join(got, "object_id"))


class Places:
    """Stations by square of a lattice with about two of them in each."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, y: np.ndarray):
        self.x0, self.y0 = x.min(), y.min()
        self.side = max(float(np.sqrt(np.ptp(x) * np.ptp(y) / len(x) * 2)), max(np.ptp(x), np.ptp(y)) / 1000, 1e-9)
        self.wide, self.high = (int(np.ptp(v) / self.side) + 1 for v in (x, y))
        cell = self._at(x, self.x0, self.wide) * self.high + self._at(y, self.y0, self.high)
        self.order = np.argsort(cell, kind="stable")
        self.first = np.searchsorted(cell[self.order], np.arange(self.wide * self.high + 1))
        self.rank = np.argsort(np.argsort(ids, kind="stable"), kind="stable")
        self.x, self.y = x, y

    def _at(self, v: np.ndarray, low: float, n: int) -> np.ndarray:
        return np.clip(np.floor((v - low) / self.side).astype(np.int64), 0, n - 1)

    def nearest(self, x: np.ndarray, y: np.ndarray, k: int) -> np.ndarray:
        """The k nearest stations of each place, in order of distance and id: as many columns as there are stations, at most k."""
        k = min(k, len(self.x))
        out = np.zeros((len(x), k), np.int64)
        left, reach = np.arange(len(x)), 1
        while len(left):
            ci, cj = (np.floor((v[left] - low) / self.side).astype(np.int64) for v, low in ((x, self.x0), (y, self.y0)))
            # a column of squares is one run of stations
            i = ci[:, None] + np.arange(-reach, reach + 1)
            low, high = (np.clip(cj + o, 0, self.high)[:, None] for o in (-reach, reach + 1))
            ok, i = (i >= 0) & (i < self.wide), np.clip(i, 0, self.wide - 1)
            start, stop = self.first[i * self.high + low], self.first[i * self.high + high]
            n = np.where(ok, stop - start, 0).ravel()
            own = np.repeat(np.repeat(np.arange(len(left)), i.shape[1]), n)
            st = self.order[np.repeat(start.ravel() - (np.cumsum(n) - n), n) + np.arange(n.sum())]
            d = np.hypot(x[left][own] - self.x[st], y[left][own] - self.y[st])
            by = np.lexsort((self.rank[st], d, own))
            own, st, d = own[by], st[by], d[by]
            many = np.bincount(own, minlength=len(left))
            begin = np.cumsum(many) - many
            last = begin + k - 1
            # nothing outside the squares is nearer than their border
            done = many >= k
            done[done] = (d[last[done]] < reach * self.side) | (reach > max(self.wide, self.high) + np.maximum(np.abs(ci), np.abs(cj))[done])
            out[left[done]] = st[begin[done, None] + np.arange(k)]
            left, reach = left[~done], reach * 2
        return out


#: Objects whose stations are looked for together.
CHUNK = 20_000


def _nearest(objects: DataFrame, stations: DataFrame, k: int, columns: tuple[str, ...]) -> DataFrame:
    """object_id and the columns of each of its k nearest stations (a bounded table, sent to all executors), ties to smaller ids."""
    kinds = {f.name: f.dataType.simpleString() for f in stations.schema.fields}
    st = stations.select(*dict.fromkeys(("station_id", "x", "y", *columns))).where("x is not null and y is not null").toPandas()
    schema = ", ".join(["object_id string", *[f"{c} {kinds[c]}" for c in columns]])
    if not len(st):
        return objects.sparkSession.createDataFrame([], schema)
    shared = objects.sparkSession.sparkContext.broadcast((Places(*[st[c].to_numpy() for c in ("station_id", "x", "y")]), st[list(columns)]))

    def found(parts):
        places, values = shared.value
        for part in parts:
            for first in range(0, len(part), CHUNK):
                some = part.iloc[first : first + CHUNK]
                at = places.nearest(some["x"].to_numpy(float), some["y"].to_numpy(float), k)
                rows = values.iloc[at.ravel()].reset_index(drop=True)
                rows.insert(0, "object_id", np.repeat(some["object_id"].to_numpy(), at.shape[1]))
                yield rows

    return objects.select(F.col("object_id").cast("string").alias("object_id"), "x", "y").where("x is not null and y is not null").distinct().mapInPandas(found, schema)


def nearest(objects: DataFrame, stations: DataFrame) -> DataFrame:
    return recomposed(objects.join(_nearest(objects, stations, 1, ("station_id", "u", "v")), "object_id"))


def spline_weights(places: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Weights of a thin-plate spline through the values, then of 1, x and y."""
    n = len(places)
    d2 = ((places[:, None] - places[None]) ** 2).sum(-1)
    kernel = np.where(d2 > 0, 0.5 * d2 * np.log(np.maximum(d2, 1e-300)), 0.0)
    plane = np.column_stack([np.ones(n), places])
    system = np.block([[kernel, plane], [plane.T, np.zeros((3, 3))]])
    return np.linalg.lstsq(system, np.concatenate([values, np.zeros((3, values.shape[1]))]), rcond=None)[0]


def _spline_of(at: np.ndarray, values: np.ndarray):
    """Places -> values of the splines, as a function that can be sent to tasks; for any number of stations."""
    if len(at) <= MAX_STATIONS:
        w = spline_weights(at, values)
        knots, plane = w[:-3], w[-3:]

        def few(where: np.ndarray) -> np.ndarray:
            out = np.column_stack([np.ones(len(where)), where]) @ plane
            for k in np.array_split(np.arange(len(where)), max(1, len(where) * len(at) // 2_000_000)):
                out[k] += plates.kernel(((where[k, None] - at[None]) ** 2).sum(-1)) @ knots
            return out

        return few
    # stations at one place: their mean, as least squares have it
    at, same = np.unique(at, axis=0, return_inverse=True)
    n = np.bincount(same.ravel())
    values = np.stack([np.bincount(same.ravel(), v) / n for v in values.T], 1)
    low, side = at.min(0), max(float(np.ptp(at, axis=0).max()), 1e-300)
    unit = (at - low) / side
    plate, plane = plates.fitted(unit, values)

    def many(where: np.ndarray) -> np.ndarray:
        where = (where - low) / side
        return plate.at(where) + np.column_stack([np.ones(len(where)), where]) @ plane

    return many


def spline(objects: DataFrame, stations: DataFrame) -> DataFrame:
    """Thin-plate splines of both components, solved once for the stations (a bounded table) and evaluated where the objects are."""
    schema = "object_id string, u double, v double"
    rows = stations.select("x", "y", "u", "v").where("x is not null and y is not null and u is not null and v is not null").distinct()

    def solved(parts):
        # in a task, whose Python has one thread for linear algebra
        every = pd.concat([pd.DataFrame(columns=["x", "y", "u", "v"], dtype=float), *parts], ignore_index=True).sort_values(["x", "y", "u", "v"]).to_numpy(float)
        if len(every):
            yield pd.DataFrame({"wind": [cloudpickle.dumps(_spline_of(np.ascontiguousarray(every[:, :2]), np.ascontiguousarray(every[:, 2:])))]})

    got = rows.repartition(1).mapInPandas(solved, "wind binary").first()
    if got is None:
        return recomposed(objects.join(objects.sparkSession.createDataFrame([], schema), "object_id"))
    shared = objects.sparkSession.sparkContext.broadcast(bytes(got["wind"]))

    def found(parts):
        wind = cloudpickle.loads(shared.value)
        for part in parts:
            for first in range(0, len(part), CHUNK):
                some = part.iloc[first : first + CHUNK]
                uv = wind(some[["x", "y"]].to_numpy(float))
                yield pd.DataFrame({"object_id": some["object_id"].to_numpy(), "u": uv[:, 0], "v": uv[:, 1]})

    places = objects.select(F.col("object_id").cast("string").alias("object_id"), "x", "y").where("x is not null and y is not null").distinct()
    return recomposed(objects.join(places.mapInPandas(found, schema), "object_id"))


METHODS = {"spline": spline, "idw": idw, "nearest": nearest}


def interpolate(objects: DataFrame, stations: DataFrame, method: str = "spline") -> DataFrame:
    """objects with u, v, speed, bearing of the wind where they are."""
    return METHODS[method](objects, with_components(stations))


def naive_angle(objects: DataFrame, stations: DataFrame) -> DataFrame:
    """The failing alternative: the plain mean of the two nearest stations' bearings, which may point the other way."""
    return _nearest(objects, stations, 2, ("bearing",)).groupBy("object_id").agg(F.avg("bearing").alias("bearing"))
