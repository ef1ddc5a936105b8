import numpy as np
import pyarrow as pa
from pyspark.sql import types as T

from lowrank_spark import config as C
from lowrank_spark.operators import kernel, train


def test_entries_reach_the_blocks_without_lists(spark):
    """Rows of lists are slow to move: no model sends them per entry, and the waves are worked out once."""
    im = spark.createDataFrame([(i, j, float(1 + (i * j) % 5)) for i in range(6) for j in range(5) if (i + j) % 3], "i long, j long, r double")
    cfg = C.FACTOR_PRESETS["stars"].but(F=2, D=1)
    laid = train.lay_waves(train.layout(im, cfg), ["cb"], cfg.side)
    assert not any(isinstance(f.dataType, T.ArrayType) for f in laid.schema.fields)
    rows = sorted(laid.collect(), key=lambda r: (r.place, r.i, r.j))
    assert [r.wave for r in rows] == kernel.wave_of(np.array([int(r.i) for r in rows]), np.array([int(r.j) for r in rows])).tolist()


def test_packed_lists_come_back():
    lists = [[1, 3], None, [], [2]]
    x = pa.chunked_array([pa.array(lists[:1], pa.list_(pa.int32())), pa.array(lists[1:], pa.list_(pa.int32()))])
    size, flat = train._unpacked(pa.chunked_array([train._packed(x)]), np.int32)
    assert size.tolist() == [2, 0, 0, 1] and flat.tolist() == [1, 3, 2]
    size, flat = train._unpacked(pa.chunked_array([train._packed(x).slice(3)]), np.int32)
    assert size.tolist() == [1] and flat.tolist() == [2]
