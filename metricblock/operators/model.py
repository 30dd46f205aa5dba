"""The embedding of blocking values: landmarks with coordinates, and everything placed against them."""

from __future__ import annotations

import json
import time
import uuid
from collections.abc import Sequence
from dataclasses import asdict, dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from metricblock.operators import landmarks as lm
from metricblock.operators import mds
from metricblock.operators.placement import ALL_ANCHORS, PlacementOptions, place
from metricblock.operators.records import BlockingSpec


@dataclass(frozen=True)
class Space:
    """One space: the landmark keys and their coordinates."""

    spec: BlockingSpec
    keys: list[list[str]] = field(repr=False)
    coords: np.ndarray = field(repr=False)
    trace: list[float] = field(repr=False)


@dataclass(frozen=True)
class EmbeddingModel:
    """Landmark embedding.  Queries and reference have to be placed by the same model; ``model_id`` tells."""

    spec: BlockingSpec
    spaces: tuple[Space, ...]
    placement: PlacementOptions
    model_id: str
    index_coords: str = "placed"

    @property
    def dimension(self) -> int:
        return sum(s.coords.shape[1] for s in self.spaces)

    @property
    def landmarks(self) -> int:
        return sum(len(s.keys) for s in self.spaces)

    @classmethod
    def fit(cls, keys: DataFrame, spec: BlockingSpec, K: int = 7, L: int = 300, landmarks: str = "auto", solver: str = "majorize", init: str = "classical", placement: PlacementOptions = PlacementOptions(), index_coords: str = "placed", seed: int = 42) -> EmbeddingModel:
        """Train on distinct keys ``(key_id, key)``: landmarks, their dissimilarities, their coordinates.

        The driver holds an L x L matrix, so L has to stay within ``mds.DRIVER_ROWS``.
        """
        if L > mds.DRIVER_ROWS:
            raise ValueError(f"at most {mds.DRIVER_ROWS} landmarks")
        spaces = []
        for i, part in enumerate(spec.parts()):
            own = keys if len(spec.parts()) == 1 else keys.select(F.array(F.get("key", F.lit(i))).alias("key")).distinct()
            combine = "sum" if part.combine == "split_space" else part.combine
            chosen = lm.choose(own, L, landmarks, seed, combine)
            delta = mds.landmark_delta(chosen, combine, part.weights)
            coords, trace = mds.lsmds(delta, K, solver, init=init, seed=seed)
            spaces.append(Space(part, chosen, coords, trace))
        return cls(spec, tuple(spaces), placement, uuid.uuid4().hex, index_coords)

    def transform(self, keys: DataFrame, id_col: str = "key_id", more: Sequence[str] = ()) -> DataFrame:
        """``(id, key, *more, coords, loss)`` of any keys, by their distances to the landmarks alone.

        With ``index_coords="mds"`` landmarks keep the coordinates they were trained to; with
        "placed" they are placed like all others, so that equal keys share a point.
        """
        out = None
        for i, space in enumerate(self.spaces):
            own = keys.select(id_col, "key", *more)
            if len(self.spaces) > 1:
                own = own.withColumns({"_whole": F.col("key"), "key": F.array(F.get("key", F.lit(i)))})
            combine = "sum" if space.spec.combine == "split_space" else space.spec.combine
            # the columns besides the key ride along, once
            ride = ("key", *more) if len(self.spaces) == 1 else ("key", "_whole", *more)
            placed = place(own, space.keys, space.coords, self.placement, id_col, combine, space.spec.weights, ride)
            if self.index_coords == "mds":
                fixed = keys.sparkSession.createDataFrame([(k, c) for k, c in zip(space.keys, space.coords.tolist(), strict=True)], "key array<string>, fixed array<double>")
                placed = placed.join(F.broadcast(fixed), "key", "left").withColumn("coords", F.coalesce("fixed", "coords")).drop("fixed")
            if len(self.spaces) > 1:
                placed = placed.withColumn("key", F.col("_whole")).drop("_whole")
                if out is not None:
                    placed = placed.select(id_col, F.col("coords").alias("_c"), F.col("loss").alias("_l"))
            out = placed if out is None else out.join(placed, id_col).withColumns({"coords": F.concat("coords", "_c"), "loss": F.col("loss") + F.col("_l")}).drop("_c", "_l")
        return out.select(id_col, "key", *more, "coords", "loss")

    def save(self, spark: SparkSession, path: str) -> None:
        rows = [(i, j, k, c) for i, s in enumerate(self.spaces) for j, (k, c) in enumerate(zip(s.keys, s.coords.tolist(), strict=True))]
        spark.createDataFrame(rows, "space int, lm_ord int, key array<string>, coords array<double>").coalesce(1).write.mode("overwrite").parquet(f"{path}/landmarks")
        manifest = {"spec": asdict(self.spec), "placement": asdict(self.placement), "model_id": self.model_id, "index_coords": self.index_coords, "traces": [s.trace for s in self.spaces]}
        spark.createDataFrame([(json.dumps(manifest),)], "manifest string").coalesce(1).write.mode("overwrite").parquet(f"{path}/manifest")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> EmbeddingModel:
        m = json.loads(spark.read.parquet(f"{path}/manifest").first()[0])
        spec = BlockingSpec(**{k: tuple(v) if isinstance(v, list) else v for k, v in m["spec"].items()})
        rows = spark.read.parquet(f"{path}/landmarks").orderBy("space", "lm_ord").collect()
        spaces = []
        for i, part in enumerate(spec.parts()):
            own = [r for r in rows if r["space"] == i]
            spaces.append(Space(part, [r["key"] for r in own], np.array([r["coords"] for r in own]), m["traces"][i]))
        return cls(spec, tuple(spaces), PlacementOptions(**m["placement"]), m["model_id"], m["index_coords"])


def place_against_all(keys: DataFrame, embedded: DataFrame, options: PlacementOptions = PlacementOptions(), combine: str = "sum") -> DataFrame:
    """Placement against every embedded value ``(key, coords)``: the un-scaled form, refused for large tables."""
    rows = embedded.select("key", "coords").limit(ALL_ANCHORS + 1).collect()
    if len(rows) > ALL_ANCHORS:
        raise ValueError(f"over {ALL_ANCHORS} anchors: use landmarks")
    rows.sort(key=lambda r: r["key"])
    return place(keys, [r["key"] for r in rows], np.array([r["coords"] for r in rows]), options, combine=combine, more=("key",))


def complete_embedding(keys: DataFrame, K: int = 7, solver: str = "majorize", init: str = "classical", seed: int = 42, combine: str = "sum", force: bool = False) -> tuple[DataFrame, list[float]]:
    """Every key scaled with every other: on the driver if few, in blocks if more, refused beyond."""
    n = keys.count()
    if n > mds.DRIVER_ROWS or solver == "distributed":
        return mds.lsmds_distributed(keys, K, seed=seed, combine=combine, force=force)
    rows = keys.select("key_id", "key").orderBy("key", "key_id").collect()
    coords, trace = mds.lsmds(mds.landmark_delta([r["key"] for r in rows], combine), K, solver, init=init, seed=seed)
    return keys.sparkSession.createDataFrame([(r["key_id"], r["key"], c) for r, c in zip(rows, coords.tolist(), strict=True)], "key_id long, key array<string>, coords array<double>"), trace


def sweep_dimension(keys: DataFrame, Ks: Sequence[int], L: int = 300, landmarks: str = "random", init: str = "random", seed: int = 42) -> DataFrame:
    """``(k, stress, seconds)`` of landmark scaling: where the curve flattens is the dimension to take."""
    spark = keys.sparkSession
    delta = mds.landmark_delta(lm.choose(keys, L, landmarks, seed))
    rows = []
    for k in Ks:
        began = time.perf_counter()
        x, _ = mds.lsmds(delta, k, init=init, seed=seed)
        rows.append((k, mds.stress_of(delta, x), time.perf_counter() - began))
    return spark.createDataFrame(rows, "k int, stress double, seconds double")
