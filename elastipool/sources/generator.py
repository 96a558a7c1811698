"""The burst-then-steady arrival curve as a Python data source, for batch reads and for streams that replay it."""

from __future__ import annotations

from pyspark.sql import SparkSession

from elastipool.model import ArrivalSpec

FORMAT = "two_phase"


def register(spark: SparkSession) -> str:
    """Register the source; options: n, window_ms, burst_pm, ratio_tenths, and for streams per_batch. Rows are (seq, enq_ms) in sequence order.

    The classes are made here, so that they travel to the workers by value and need nothing of this package there.
    """
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

    default = ArrivalSpec()

    class Curve:
        def __init__(self, options):
            get = lambda k, v: int(options.get(k, v))
            self.n, self.per_batch = get("n", 200), get("per_batch", 50)
            window, beta, ratio = get("window_ms", default.window_ms), get("burst_pm", default.burst_pm), get("ratio_tenths", default.ratio_tenths)
            b, s = beta * ratio, (1000 - beta) * 10
            self.burst, self.edge, self.window = (self.n * b + (b + s) // 2) // (b + s), window * beta // 1000, window

        def at(self, i):
            if i < self.burst:
                return i * self.edge // self.burst
            return self.edge + (i - self.burst) * (self.window - self.edge) // max(self.n - self.burst, 1)

    class Rows:
        """An iterator that the stream's cache can copy, so a batch is never held as a list."""

        def __init__(self, curve, a, z):
            self.curve, self.i, self.end = curve, a, z

        def __iter__(self):
            return self

        def __next__(self):
            if self.i >= self.end:
                raise StopIteration
            self.i += 1
            return self.i - 1, self.curve.at(self.i - 1)

    class Batch(DataSourceReader):
        def __init__(self, options):
            self.curve = Curve(options)

        def partitions(self):
            step = max(1, -(-self.curve.n // 8))
            return [InputPartition((a, min(a + step, self.curve.n))) for a in range(0, max(self.curve.n, 1), step)]

        def read(self, part):
            return Rows(self.curve, *part.value)

    class Stream(SimpleDataSourceStreamReader):
        def __init__(self, options):
            self.curve = Curve(options)

        def initialOffset(self):
            return {"seq": 0}

        def read(self, start):
            end = min(start["seq"] + self.curve.per_batch, self.curve.n)
            return Rows(self.curve, start["seq"], end), {"seq": end}

        def readBetweenOffsets(self, start, end):
            return Rows(self.curve, start["seq"], end["seq"])

        def commit(self, end):
            pass

    class TwoPhase(DataSource):
        @classmethod
        def name(cls):
            return FORMAT

        def schema(self):
            return "seq long, enq_ms long"

        def reader(self, schema):
            return Batch(self.options)

        def simpleStreamReader(self, schema):
            return Stream(self.options)

    spark.dataSource.register(TwoPhase)
    return FORMAT
