"""Well-known binary of 3-D lines, by an Arrow function (little endian, type 1002)."""

from __future__ import annotations

import struct

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType


def line_z(points: np.ndarray) -> bytes:
    """points: n x 3 numbers in the order in which they are written."""
    return struct.pack("<BII", 1, 1002, len(points)) + np.ascontiguousarray(points, "<f8").tobytes()


def read_line_z(data: bytes) -> np.ndarray:
    order, kind, n = struct.unpack("<BII", data[:9])
    if (order, kind) != (1, 1002):
        raise ValueError("not a little-endian 3-D line")
    return np.frombuffer(data, "<f8", 3 * n, 9).reshape(n, 3)


@F.arrow_udf(BinaryType())
def _lines(flat: pa.Array) -> pa.Array:
    return pa.array([None if x is None else line_z(np.asarray(x, np.float64).reshape(-1, 3)) for x in flat.to_pylist()], pa.binary())


def to_wkb_z(segments: Column, axis: str = "latlon") -> Column:
    one, two = ("lat", "lon") if axis == "latlon" else ("lon", "lat")
    flat = F.flatten(F.transform(F.flatten(segments), lambda p: F.array(p[one], p[two], F.coalesce(p["ele"], F.lit(float("nan"))))))
    return _lines(flat)
