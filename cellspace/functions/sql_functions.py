"""SQL-callable forms: table functions over boxes and covers, and the Arrow leaf lookup."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.functions import arrow_udf, udtf


@udtf(returnType="cell long")
class CellsInBox:
    """cells_in_box(layer, lo, hi): cells of a layer of the unit box that meet a box, row-major."""

    def eval(self, layer: int, lo: list, hi: list):
        per = 1 << layer
        cells = [0]
        for a, b in zip(lo, hi, strict=True):
            first, last = (max(0, min(per - 1, int(np.floor(v * per)))) for v in (a, b))
            cells = [c * per + k for c in cells for k in range(first, last + 1)]
        for c in cells:
            yield (c,)


@udtf(returnType="node_id long, height int, first_leaf long, last_leaf long")
class KdNodes:
    """kd_nodes(levels): post-order numbers of a balanced tree with their leaf intervals."""

    def eval(self, levels: int):
        for h in range(levels + 1):
            for n in range(1 << (levels - h)):
                first, last = n << h, ((n + 1) << h) - 1
                yield (2 * last - bin(last).count("1") + 1 + h, h, first, last)


def leaf_udf(tree):
    """locate_leaf(x0, x1, ...) over a tree, in Arrow batches."""

    @arrow_udf("long")
    def locate_leaf(*cols: pa.Array) -> pa.Array:
        return pa.array(tree.locate(np.stack([np.asarray(c) for c in cols], 1)))

    return locate_leaf


def register(spark: SparkSession, tree=None) -> None:
    spark.udtf.register("cells_in_box", CellsInBox)
    spark.udtf.register("kd_nodes", KdNodes)
    if tree is not None:
        spark.udf.register("locate_leaf", leaf_udf(tree))
