"""Density models as tables: made once, saved, and followed by as many branch passes as wanted."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from spurline.operators import kernels as K
from spurline.params import BranchParams
from spurline.plans.clustering import RESULT, _points, spread

MODEL = "grp string, id long, x array<double>, label int, strength double, core double, tree_nbr long, tree_w double"


def density_model(points: DataFrame, p: BranchParams = BranchParams()) -> DataFrame:
    """MODEL rows: each point's label, strength and core distance, and the edge by which it joined the spanning tree (null for the first)."""
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        grp = pdf["grp"].iloc[0]
        pdf, x = _points(pdf)
        m, ids = K.density(x, p), pdf["id"].to_numpy()
        near: list = [None] * len(ids)
        far: list = [None] * len(ids)
        for a, b, w in m.tree:
            near[int(b)], far[int(b)] = int(ids[int(a)]), float(w)
        return pd.DataFrame({"grp": grp, "id": ids, "x": pdf["x"].tolist(), "label": m.label, "strength": m.strength, "core": m.core, "tree_nbr": pd.array(near, "Int64"), "tree_w": pd.array(far, "Float64")})

    return spread(points, p.metric).groupBy("grp").applyInPandas(run, MODEL)


def branches_of(model: DataFrame, p: BranchParams) -> DataFrame:
    """RESULT rows from a density model: neighbours, tree and clusters are taken from it and not found again.

    Ids are distinct within a group.
    """
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        grp = pdf["grp"].iloc[0]
        pdf, x = _points(pdf)
        ids = pdf["id"].to_numpy()
        place = {int(a): i for i, a in enumerate(ids)}
        core, d = pdf["core"].to_numpy(float), K.distances(x, p.metric)
        tree = np.array([(place[int(a)], i, w) for i, (a, w) in enumerate(zip(pdf["tree_nbr"], pdf["tree_w"], strict=True)) if pd.notna(a)]).reshape(-1, 3)
        m = K.Density(d, core, np.maximum(d, np.maximum(core[:, None], core[None, :])), tree, K.Tree(), pdf["label"].to_numpy(int), pdf["strength"].to_numpy(float))
        return pd.DataFrame({"grp": grp, "id": ids, **K.combine(m, K.branches(x, m, p), p)})

    return model.groupBy("grp").applyInPandas(run, RESULT)


def save_model(model: DataFrame, p: BranchParams, path: str) -> None:
    """The model as Parquet, and its parameters as JSON lines beside it, in a folder that all executors share."""
    model.write.parquet(f"{path}/points")
    model.sparkSession.createDataFrame([(p.to_json(),)], "value string").coalesce(1).write.text(f"{path}/params")


def load_model(spark: SparkSession, path: str) -> tuple[DataFrame, BranchParams]:
    import json

    return spark.read.schema(MODEL).parquet(f"{path}/points"), BranchParams(**json.loads(spark.read.text(f"{path}/params").first()[0]))
