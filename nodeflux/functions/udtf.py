"""Table functions for SQL users."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="pos: int")
class SkipPositions:
    """Places 1 .. deg, each with chance p, by geometric gaps keyed by (seed, key)."""

    def eval(self, deg: int, p: float, seed: int, key: int) -> Iterator[tuple[int]]:
        import math

        from nodeflux.functions.rng import u01_np

        if p >= 1:
            yield from ((i,) for i in range(1, deg + 1))
            return
        at, draw, scale = 0, 0, math.log1p(-p)
        while p > 0:
            gap = 1 + math.floor(math.log(float(u01_np(seed, key, draw))) / scale)
            at, draw = at + min(gap, deg + 1), draw + 1
            if at > deg:
                return
            yield (at,)


def register(spark: SparkSession) -> None:
    """skip_positions(deg, p, seed, key) for SQL."""
    import sys

    from nodeflux.functions import rng
    from pyspark import cloudpickle

    for module in (rng, sys.modules[__name__]):
        cloudpickle.register_pickle_by_value(module)
    spark.udtf.register("skip_positions", SkipPositions)
