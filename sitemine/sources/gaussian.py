"""Synthetic sources as Spark data sources: Gaussian mixtures and basket generators.

``spark.dataSource.register(GaussianMixture)``, then ``spark.read.format("gaussian_mixture")``.
Every row is a function of (seed, partition), so a lost partition is made again alike.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

_BATCH = 50_000


class _Part(InputPartition):
    def __init__(self, site: int, first: int, rows: int):
        self.site, self.first, self.rows = site, first, rows


def _parts(options: dict, rows_name: str, default: int) -> list[_Part]:
    sites, rows = int(options.get("sites", 5)), int(options.get(rows_name, default))
    most = int(options.get("rowsperpartition", 200_000))
    return [_Part(s, first, min(most, rows - first)) for s in range(sites) for first in range(0, rows, most)]


class GaussianMixture(DataSource):
    """Points of planted Gaussians: options sites, points (per site), groups, dims, box, sd, seed."""

    @classmethod
    def name(cls) -> str:
        return "gaussian_mixture"

    def schema(self) -> str:
        return "site int, point_id bigint, features array<double>, label int"

    def reader(self, schema) -> DataSourceReader:
        return _GaussianReader(dict(self.options))


class _GaussianReader(DataSourceReader):
    def __init__(self, options: dict):
        self.options = {k.lower(): v for k, v in options.items()}

    def partitions(self) -> list[_Part]:
        return _parts(self.options, "points", 1200)

    def read(self, part: _Part) -> Iterator[pa.RecordBatch]:
        get = self.options.get
        groups, dims, box, sd, seed = int(get("groups", 6)), int(get("dims", 2)), float(get("box", 40)), float(get("sd", 2)), int(get("seed", 42))
        centers = np.random.default_rng(seed).uniform(-box, box, (groups, dims))
        rng = np.random.default_rng([seed, part.site, part.first])
        for at in range(0, part.rows, _BATCH):
            n = min(_BATCH, part.rows - at)
            label = rng.integers(0, groups, n)
            x = centers[label] + rng.normal(0, sd, (n, dims))
            ids = (np.int64(part.site) << 40) + part.first + at + np.arange(n)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * dims), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(n, part.site, np.int32)), pa.array(ids), lists, pa.array(label.astype(np.int32))], names=["site", "point_id", "features", "label"]
            )


class BasketGenerator(DataSource):
    """Transactions with planted patterns: options sites, baskets (per site), items, length, patterns, seed."""

    @classmethod
    def name(cls) -> str:
        return "basket_gen"

    def schema(self) -> str:
        return "site int, tid bigint, items array<int>"

    def reader(self, schema) -> DataSourceReader:
        return _BasketReader(dict(self.options))


class _BasketReader(DataSourceReader):
    def __init__(self, options: dict):
        self.options = {k.lower(): v for k, v in options.items()}

    def partitions(self) -> list[_Part]:
        return _parts(self.options, "baskets", 1000)

    def read(self, part: _Part) -> Iterator[pa.RecordBatch]:
        get = self.options.get
        items, length, patterns, seed = int(get("items", 100)), int(get("length", 8)), int(get("patterns", 10)), int(get("seed", 42))
        shared = np.random.default_rng(seed)
        planted = [shared.choice(items, 4, replace=False) for _ in range(patterns)]
        rng = np.random.default_rng([seed, part.site, part.first])
        for at in range(0, part.rows, _BATCH):
            n = min(_BATCH, part.rows - at)
            rows = []
            for _ in range(n):
                own = set(rng.integers(0, items, max(1, rng.poisson(length / 2))).tolist())
                if patterns and rng.random() < 0.5:
                    own |= set(planted[rng.integers(0, patterns)].tolist())
                rows.append(sorted(own))
            ids = (np.int64(part.site) << 40) + part.first + at + np.arange(n)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(n, part.site, np.int32)), pa.array(ids), pa.array(rows, pa.list_(pa.int32()))], names=["site", "tid", "items"])


def register(spark) -> None:
    spark.dataSource.register(GaussianMixture)
    spark.dataSource.register(BasketGenerator)
