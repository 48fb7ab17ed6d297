"""The distances and the detector under SQL names."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from seqnorm.functions import distance as D
from seqnorm.functions.table_functions import ContiguousClusters, LivingDetect, SlidingWindows
from seqnorm.session import ship


def _pairwise(fn):  # noqa: ANN001, ANN202
    def run(a: pd.Series, b: pd.Series) -> pd.Series:
        return pd.Series([None if x is None or y is None else fn(np.asarray(x, float), np.asarray(y, float)) for x, y in zip(a, b)])

    return pandas_udf(run, "double")


def dtw(a: pd.Series, b: pd.Series) -> pd.Series:
    """Warping distances; pairs of equal shape go through one table together."""
    out, alike = pd.Series(np.nan, index=a.index), {}
    for i, (x, y) in enumerate(zip(a, b)):
        if x is not None and y is not None:
            alike.setdefault((len(x), len(y)), []).append(i)
    for (n, m), at in alike.items():
        if n and m:
            out.iloc[at] = D.dtw_rows(np.stack(a.iloc[at].to_list()).astype(float), np.stack(b.iloc[at].to_list()).astype(float))
        else:
            out.iloc[at] = [D.dtw(np.asarray(a.iloc[i], float), np.asarray(b.iloc[i], float)) for i in at]
    return out


def phi(d: pd.Series, tau: pd.Series, eta: pd.Series) -> pd.Series:
    return pd.Series(np.where(d <= tau, 1.0, np.exp(-eta * (d - tau).clip(lower=0))))


def centroid(xs: pd.Series) -> list[float]:
    """Pointwise mean of centred arrays (an aggregate)."""
    return D.prepare(np.stack(xs.to_numpy()).astype(float), "zm").mean(0).tolist()


def auc(score: pd.Series, y: pd.Series) -> float:
    """AUC of a group (an aggregate); for groups that fit a task."""
    r = score.rank().to_numpy()
    pos = (y > 0).to_numpy()
    p, n = pos.sum(), (~pos).sum()
    return float((r[pos].sum() - p * (p + 1) / 2) / (p * n)) if p and n else float("nan")


def register(spark: SparkSession) -> None:
    ship(spark)
    named = {"zm_dist": D.zm, "zn_dist": D.zn, "sbd_dist": D.sbd, "min_place": lambda p, w: D.min_place(p, w)[0]}
    for name, fn in named.items():
        spark.udf.register(name, _pairwise(fn))
    spark.udf.register("dtw_dist", pandas_udf(dtw, "double"))
    spark.udf.register("phi", pandas_udf(phi, "double"))
    spark.udf.register("centroid", pandas_udf(centroid, "array<double>"))
    spark.udf.register("auc", pandas_udf(auc, "double"))
    for name, cls in {"living_detect": LivingDetect, "sliding_windows": SlidingWindows, "contiguous_clusters": ContiguousClusters}.items():
        spark.udtf.register(name, udtf(cls))
