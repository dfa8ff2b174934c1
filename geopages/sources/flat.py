"""Geometries of an Arrow batch as flat arrays, and records of bytes made and read by array work."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa


@dataclass(frozen=True)
class Flat:
    #: Kind of each geometry; -1 is null.
    kind: np.ndarray
    n_parts: np.ndarray
    n_coords: np.ndarray
    #: (coordinates, 2)
    xy: np.ndarray

    @property
    def part_geometry(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.kind)), self.n_parts)

    @property
    def first_part(self) -> np.ndarray:
        """First part of each geometry, and their number at the end."""
        return np.r_[0, np.cumsum(self.n_parts)]

    @property
    def first_coord(self) -> np.ndarray:
        return np.r_[0, np.cumsum(self.n_coords)]

    def opens(self) -> np.ndarray:
        """True for rings that begin a polygon: a geometry's first one, and clockwise ones."""
        at = self.first_coord
        xy = self.xy - np.repeat(self.xy[at[:-1][self.n_coords > 0]], self.n_coords[self.n_coords > 0], axis=0)
        cross = np.zeros(len(xy) + 1)
        if len(xy) > 1:
            cross[: len(xy) - 1] = xy[:-1, 0] * xy[1:, 1] - xy[1:, 0] * xy[:-1, 1]
        cross[at[1:][self.n_coords > 0] - 1] = 0  # no step from one ring into the next
        area = np.zeros(len(self.n_coords))
        has = np.flatnonzero(self.n_coords > 0)
        if len(has):
            area[has] = np.add.reduceat(cross, at[:-1][has])
        out = area < 0
        out[self.first_part[:-1][self.n_parts > 0]] = True
        return out

    def take(self, rows: np.ndarray) -> Flat:
        """The geometries of a mask or list of places, in their order."""
        rows = np.flatnonzero(rows) if rows.dtype == bool else rows
        parts = spread(self.first_part[:-1][rows], self.n_parts[rows])
        coords = spread(self.first_coord[:-1][parts], self.n_coords[parts])
        return Flat(self.kind[rows], self.n_parts[rows], self.n_coords[parts], self.xy[coords])


def spread(first: np.ndarray, count: np.ndarray, step: int = 1) -> np.ndarray:
    """first, first + step, ... of each run, end to end."""
    count = np.asarray(count, np.int64)
    within = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
    return np.repeat(np.asarray(first, np.int64), count) + step * within


def flat(g: pa.StructArray) -> Flat:
    from .page_table import _rows

    kind, n_parts, n_coords, x, y, *_ = _rows(g)
    return Flat(kind, n_parts, n_coords, np.stack([x, y], 1))


def nested(f: Flat, kind: pa.StructType) -> pa.StructArray:
    """Back to geometries of the Arrow type ``kind``."""
    parts_type = kind.field("parts").type
    leaf = pa.StructArray.from_arrays([pa.array(np.ascontiguousarray(f.xy[:, i])) for i in (0, 1)], fields=list(parts_type.value_type.value_type))
    inner = pa.ListArray.from_arrays(pa.array(f.first_coord.astype(np.int32)), leaf, type=parts_type.value_type)
    parts = pa.ListArray.from_arrays(pa.array(f.first_part.astype(np.int32)), inner, type=parts_type)
    return pa.StructArray.from_arrays([pa.array(np.maximum(f.kind, 0).astype(np.int32)), parts], fields=list(kind), mask=pa.array(f.kind < 0))


class Bytes:
    """A byte string written and read at many places at once."""

    def __init__(self, data: int | np.ndarray):
        self.data = np.zeros(data, np.uint8) if isinstance(data, (int, np.integer)) else data

    def put(self, at: np.ndarray, values, kind: str) -> None:
        """Numbers of a NumPy type at byte places ``at``."""
        at = np.asarray(at, np.int64)
        values = np.broadcast_to(np.asarray(values), at.shape)
        raw = np.ascontiguousarray(values, np.dtype(kind)).view(np.uint8).reshape(len(at), np.dtype(kind).itemsize)
        for k in range(raw.shape[1]):
            self.data[at + k] = raw[:, k]

    def get(self, at: np.ndarray, kind: str) -> np.ndarray:
        at = np.asarray(at, np.int64)
        size = np.dtype(kind).itemsize
        raw = np.empty((len(at), size), np.uint8)
        for k in range(size):
            raw[:, k] = self.data[at + k]
        return raw.view(np.dtype(kind)).ravel()

    def cut(self, sizes: np.ndarray, missing: np.ndarray | None = None) -> pa.Array:
        """Consecutive pieces as a binary array; ``missing`` ones are null."""
        ends = np.r_[0, np.cumsum(sizes)].astype(np.int32)
        mask = None if missing is None or not missing.any() else pa.py_buffer(np.packbits(~missing, bitorder="little"))
        return pa.Array.from_buffers(pa.binary(), len(sizes), [mask, pa.py_buffer(ends), pa.py_buffer(self.data)])


def raw(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of a binary column and each value's bounds; null is empty."""
    _, offsets, data = col.buffers()
    at = np.frombuffer(offsets, np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    return np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8), at
