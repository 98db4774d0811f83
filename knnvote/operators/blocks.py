"""Points as packed blocks, for methods that pass over them many times, and leaf codes packed the same way.

A row is a block of points: the bytes of their ids and of their vectors. Such a row goes from a file into a task's arrays
as it is, where lists of numbers are copied one number at a time.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.storage import settle
from .projection import block

BLOCK_NUMBERS = 1 << 18  # numbers in a block: 2 MB of doubles
_PACKED = "ids binary, rows binary"


def _bytes(x: np.ndarray) -> pa.Array:
    return pa.array([np.ascontiguousarray(x).tobytes()], pa.binary())


@dataclass(frozen=True)
class Blocks:
    """Ids with a row of `width` numbers each."""

    table: DataFrame  # ids, rows
    width: int
    kind: str

    def map(self, run: Callable[[Iterator], Iterator], schema: str) -> DataFrame:
        """Rows that run(iterator of ids and matrix) gives for the blocks of a task, as record batches; vectors come as doubles."""
        width, kind = self.width, self.kind

        def whole(batches):
            return run((np.frombuffer(ids.as_buffer(), np.int64), _wide(rows.as_buffer(), kind, width)) for b in batches for ids, rows in zip(b.column(0), b.column(1), strict=True))

        return self.table.mapInArrow(whole, schema)

    def cells(self) -> DataFrame:
        """(part, cell, id): a row for each id and each of its numbers."""
        def run(blocks):
            for ids, codes in blocks:
                part = np.tile(np.arange(codes.shape[1], dtype=np.int32), len(codes))
                yield pa.record_batch([pa.array(part), pa.array(codes.astype(np.int64).ravel()), pa.array(np.repeat(ids, codes.shape[1]))], names=["part", "cell", "id"])

        return self.map(run, "part int, cell long, id long")

    def coded(self, code: Callable[[np.ndarray], np.ndarray], width: int, name: str) -> Blocks:
        """Blocks of the same ids with the whole numbers that `code` gives for the rows, written into the shared folder."""
        def run(blocks):
            for ids, x in blocks:
                yield pa.record_batch([_bytes(ids), _bytes(code(x).astype(np.int64))], names=["ids", "rows"])

        return Blocks(settle(self.map(run, _PACKED), name), width, "<i8")

    def vectors(self, ids: list[int]) -> dict[int, np.ndarray]:
        """The rows of a few ids, in the driver."""
        asked = np.array(sorted(ids), np.int64)

        def run(blocks):
            for own, x in blocks:
                at = np.flatnonzero(np.isin(own, asked))
                for i in at:
                    yield pa.record_batch([pa.array(own[i : i + 1]), _bytes(x[i])], names=["id", "row"])

        return {r["id"]: np.frombuffer(r["row"]) for r in self.map(run, "id long, row binary").collect()}


def _wide(data, kind: str, width: int) -> np.ndarray:
    x = np.frombuffer(data, kind).reshape(-1, width)
    return x if kind == "<i8" else x.astype(np.float64)


def packed(points: DataFrame, d: int | None = None) -> Blocks:
    """Points (id, vec) as blocks in the shared folder; floats stay floats."""
    d = d or points.select(F.max(F.size("vec"))).first()[0]
    kind = "<f4" if points.schema["vec"].dataType.elementType.typeName() == "float" else "<f8"
    rows = max(1, BLOCK_NUMBERS // d)

    def run(batches):
        ids, vecs, held = [], [], 0
        for b in batches:
            for at in range(0, b.num_rows, rows):
                part = b.slice(at, rows)
                ids.append(part.column(0).to_numpy())
                vecs.append(block(part.column(1), d).astype(kind))
                held += part.num_rows
                if held >= rows:
                    yield pa.record_batch([_bytes(np.concatenate(ids)), _bytes(np.concatenate(vecs))], names=["ids", "rows"])
                    ids, vecs, held = [], [], 0
        if ids:
            yield pa.record_batch([_bytes(np.concatenate(ids)), _bytes(np.concatenate(vecs))], names=["ids", "rows"])

    # bytes are read as they lie, so files are split evenly among tasks
    table = settle(points.select("id", "vec").mapInArrow(run, _PACKED), "packed", BLOCK_NUMBERS, compression="uncompressed")
    return Blocks(table, d, kind)
