"""Which scheme, kernel and engine a fit takes, from sizes alone; explained as a table."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from gradvb.estimators import DRIVER_NUMBERS
from gradvb.sampling import BROADCAST_INDEX
from gradvb.sums import COLUMN_DIM


@dataclass(frozen=True)
class Plan:
    """The choices and why."""

    scheme: str
    exact_kernel: str
    engine: str
    index_join: str
    tiles: int
    reason: str

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(self.scheme, self.exact_kernel, self.engine, self.index_join, self.tiles, self.reason)], "scheme string, exact_kernel string, engine string, index_join string, tiles int, reason string")


def plan_fit(n: int, d: int, m: float, draws: int, block: int = 10, tile_rows: int = 2_000_000) -> Plan:
    """Small samples are fetched for several iterations at once; large ones are summed where they lie; shares beyond a tenth read whole tiles."""
    rows = max(1, round(m * n)) if m < 1 else int(m)
    numbers = rows * block * (d + 3)
    share = rows / max(n, 1)
    scheme = "tile" if share >= 0.1 and rows > BROADCAST_INDEX else "replacement"
    engine = "driver" if numbers <= DRIVER_NUMBERS and scheme == "replacement" else "spark"
    kernel = "column" if d <= COLUMN_DIM else "block"
    join = "broadcast" if rows <= BROADCAST_INDEX else "shuffle"
    return Plan(scheme, kernel, engine, join, max(16, -(-n // tile_rows)), f"n={n}, d={d}, m={rows} ({share:.2%}), {draws} draws, {numbers} sampled numbers a block")
