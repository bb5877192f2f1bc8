"""Functions over whole texts as Arrow functions that hold few of them at once.

Spark hands a worker a batch of texts, bounded by rows and by bytes in the session's settings; the JVM holds a batch and
its serialised form at once. So a session that allows more than ``ROWS`` rows a batch is set to ``ROWS`` (a side effect:
there is no such setting for a plan). In the worker only ``SLICE`` texts at a time are turned into Python objects.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DataType, _parse_datatype_string

SLICE, ROWS = 256, 1000
_SETTING = "spark.sql.execution.arrow.maxRecordsPerBatch"


def by_row(make: Callable[[], Callable], returns: str, binary: bool = False):
    """A column function that applies ``make()(value)`` to each value; ``make`` is called once a batch in the worker.

    A null counts as the empty text (``binary``: empty bytes). Structs are given as tuples in order of fields.
    """
    conf = SparkSession.active().conf
    if not 0 < int(conf.get(_SETTING)) <= ROWS:
        conf.set(_SETTING, ROWS)
    kind = _arrow(_parse_datatype_string(returns))
    names = [f.name for f in kind] if pa.types.is_struct(kind) else None
    blank = b"" if binary else ""

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        one = make()
        for batch in batches:
            for at in range(0, len(batch), SLICE):
                values = [one(blank if v is None else v) for v in batch.slice(at, SLICE).to_pylist()]
                if names is None:
                    yield pa.array(values, kind)
                else:
                    columns = list(zip(*values, strict=True))
                    yield pa.StructArray.from_arrays([pa.array(c, kind.field(n).type) for c, n in zip(columns, names, strict=True)], names)
            if not len(batch):
                yield pa.array([], kind)

    run.__annotations__ = {"batches": Iterator[pa.Array], "return": Iterator[pa.Array]}
    return F.arrow_udf(run, returns)


def _arrow(kind: DataType) -> pa.DataType:
    from pyspark.sql.pandas.types import to_arrow_type

    return to_arrow_type(kind)
