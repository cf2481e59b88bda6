"""Extension points: Arrow functions that agree with the native expressions, and table functions for SQL."""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from .hypergraph import Hypergraph
from .measures import exponents


def degree_bucket_udf():
    """degree_bucket() as a pandas function."""

    @F.pandas_udf("int")
    def bucket(deg: pd.Series) -> pd.Series:
        d = deg.to_numpy().astype(np.int64)
        return pd.Series([0 if x <= 1 else int(x - 1).bit_length() for x in d]).astype("int32")

    return bucket


def max_degree_udf():
    """Largest count, as a grouped pandas function."""

    @F.pandas_udf("long")
    def most(cnt: pd.Series) -> int:
        return int(cnt.max()) if len(cnt) else 0

    return most


def register_table_functions(spark: SparkSession) -> None:
    """grid_cells(coordinates, shares): the cells of a tuple, -1 standing for a variable it lacks. hypergraph_measures(edges): measures of a
    hypergraph given as JSON, one row for each."""

    @F.udtf(returnType="cell: int")
    class GridCells:
        def eval(self, coords: list, shares: list):
            cells, step = [0], 1
            for c, s in zip(coords, shares, strict=True):
                cells = [x + step * v for x in cells for v in (range(s) if c < 0 else [c])]
                step *= s
            for x in sorted(cells):
                yield (x,)

    @F.udtf(returnType="measure: string, value: string")
    class HypergraphMeasures:
        def eval(self, edges: str):
            found = exponents(Hypergraph.of(json.loads(edges)))
            for k in ("rho", "tau", "kappa", "psi", "phi"):
                yield k, str(found[k])

    spark.udtf.register("grid_cells", GridCells)
    spark.udtf.register("hypergraph_measures", HypergraphMeasures)
