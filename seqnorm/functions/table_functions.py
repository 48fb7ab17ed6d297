"""Table functions for SQL; importable without a session, as Spark analyses them in a worker."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult, OrderingColumn, PartitioningColumn

from seqnorm.functions import distance as D


class LivingDetect:
    """living_detect(TABLE(points) PARTITION BY series_id ORDER BY pos, ell): scores of a series by online detection."""

    @staticmethod
    def analyze(t: AnalyzeArgument, ell: AnalyzeArgument) -> AnalyzeResult:
        from pyspark.sql.types import StructType

        schema = StructType().add("series_id", "string").add("start", "long").add("score", "double").add("no_active", "boolean")
        return AnalyzeResult(schema=schema, partitionBy=[PartitioningColumn("series_id")], orderBy=[OrderingColumn("pos")])

    def __init__(self):
        self.rows: list[tuple[int, float]] = []
        self.series, self.ell = None, 50

    def eval(self, t, ell: int) -> None:  # noqa: ANN001
        self.series, self.ell = t["series_id"], ell
        self.rows.append((t["pos"], t["x"]))

    def terminate(self) -> Iterator[tuple]:
        from seqnorm.operators.living import Params, detect_series, fit_series

        if self.rows:
            x, params = np.array([r[1] for r in self.rows], float), Params(ell=self.ell)
            model = fit_series(x[: max(params.ell_m, len(x) // 5)], params)
            found = detect_series(x, model, params)
            for i in range(len(found.score)):
                yield self.series, self.rows[0][0] + i, float(found.score[i]), bool(found.no_active[i])


class SlidingWindows:
    """sliding_windows(TABLE(points) PARTITION BY series_id ORDER BY pos, ell)."""

    @staticmethod
    def analyze(t: AnalyzeArgument, ell: AnalyzeArgument) -> AnalyzeResult:
        from pyspark.sql.types import ArrayType, DoubleType, StructType

        schema = StructType().add("series_id", "string").add("start", "long").add("xs", ArrayType(DoubleType()))
        return AnalyzeResult(schema=schema, partitionBy=[PartitioningColumn("series_id")], orderBy=[OrderingColumn("pos")])

    def __init__(self):
        self.held: list[float] = []

    def eval(self, t, ell: int) -> Iterator[tuple]:  # noqa: ANN001
        self.held.append(float(t["x"]))
        if len(self.held) > ell:
            self.held.pop(0)
        if len(self.held) == ell:
            yield t["series_id"], t["pos"] - ell + 1, list(self.held)


class ContiguousClusters:
    """contiguous_clusters(TABLE(segments) PARTITION BY series_id ORDER BY seg)."""

    @staticmethod
    def analyze(t: AnalyzeArgument) -> AnalyzeResult:
        from pyspark.sql.types import StructType

        schema = StructType().add("series_id", "string").add("cluster_id", "int").add("seg", "int")
        return AnalyzeResult(schema=schema, partitionBy=[PartitioningColumn("series_id")], orderBy=[OrderingColumn("seg")])

    def __init__(self):
        self.rows: list[tuple[str, int, list[float]]] = []

    def eval(self, t) -> None:  # noqa: ANN001
        self.rows.append((t["series_id"], t["seg"], t["xs"]))

    def terminate(self) -> Iterator[tuple]:
        from seqnorm.operators.contig import cluster

        if self.rows:
            _, found = cluster(D.prepare(np.array([r[2] for r in self.rows], float), "zm"))
            for k, members in enumerate(found):
                for i in members:
                    yield self.rows[i][0], k, self.rows[i][1]
