"""What Spark itself counts while the phases of a method run: seconds and bytes, told as transfers of blocks.

The counters are those of the driver's status store, which keeps the last ``spark.ui.retainedStages`` stages. What other
threads of the session run meanwhile is counted too. A session without a driver of its own (Spark Connect) has no store.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Bytes of a block, in which transfers are told.
BLOCK = 2**12
_COLUMNS = "method string, phase string, items long, stages long, seconds double, bytes_read long, bytes_written long, bytes_spilled long, transfers long, transfers_per_item double"


class CostLedger:
    """Rows for phases: what stages read (tables, shuffles), wrote (tables, shuffles) and spilled to disk."""

    def __init__(self, spark: SparkSession, block: int = BLOCK) -> None:
        self.spark, self.block, self.rows = spark, block, []
        self._context = spark.sparkContext._jsc.sc()

    def _stages(self) -> dict[int, tuple[int, int, int]]:
        self._context.listenerBus().waitUntilEmpty()
        gateway = self.spark.sparkContext._gateway
        empty = gateway.jvm.java.util.ArrayList()
        found = self._context.statusStore().stageList(empty, False, False, gateway.new_array(gateway.jvm.double, 0), empty)
        out: dict[int, tuple[int, int, int]] = {}
        for k in range(found.size()):
            x = found.apply(k)
            mine = (x.inputBytes() + x.shuffleReadBytes(), x.outputBytes() + x.shuffleWriteBytes(), x.diskBytesSpilled())
            before = out.get(x.stageId(), (0, 0, 0))  # a stage that was tried again
            out[x.stageId()] = tuple(a + b for a, b in zip(before, mine, strict=True))
        return out

    @contextmanager
    def phase(self, method: str, phase: str, items: int) -> Iterator[None]:
        """Counts what runs inside; ``items`` is the number of nodes and edges, or of nodes, that costs are told for."""
        known, began = self._stages(), time.monotonic()
        yield
        took = time.monotonic() - began
        fresh = [v for k, v in self._stages().items() if k not in known]
        read, written, spilled = (sum(v[i] for v in fresh) for i in range(3))
        transfers = -(-(read + written + 2 * spilled) // self.block)  # what is spilled is read again
        self.rows.append((method, phase, items, len(fresh), took, read, written, spilled, transfers, transfers / max(1, items)))

    def table(self) -> DataFrame:
        """method, phase, items, stages, seconds, bytes_read, bytes_written, bytes_spilled, transfers, transfers_per_item."""
        return self.spark.createDataFrame(self.rows, _COLUMNS)
