"""Packed sketches: one binary a vertex, sparse (4-byte entries, sorted) or dense (a byte a register).

For hops where sketches fill up, and for joint estimation, which needs both register lists side by side."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.estimate import estimate_array
from ..functions.spec import SketchSpec

SPARSE, DENSE = 0, 1
SCHEMA = "x long, mode tinyint, regs binary, nz int"


def to_bytes(j: np.ndarray, rho: np.ndarray, spec: SketchSpec, dense_only: bool = False) -> tuple[int, bytes]:
    """Mode and bytes of a sketch from its nonzero registers."""
    if dense_only or len(j) > spec.dense_at * spec.r:
        out = np.zeros(spec.r, np.uint8)
        out[j] = rho
        return DENSE, out.tobytes()
    order = np.argsort(j, kind="stable")
    return SPARSE, (j[order].astype(np.uint32) << np.uint32(8) | rho[order].astype(np.uint32)).astype(np.uint32).tobytes()


def to_dense(modes, data, spec: SketchSpec) -> np.ndarray:
    """Registers of sketches, one row each (may be a read-only view)."""
    n, data = len(data), data.cast(pa.binary()) if isinstance(data, pa.Array) else pa.array(data, pa.binary())
    if not n:
        return np.zeros((0, spec.r), np.uint8)
    offsets, content = data.buffers()[1:]
    ends = np.frombuffer(offsets, np.int32)[data.offset : data.offset + n + 1]
    flat = np.frombuffer(content or b"", np.uint8)[ends[0] : ends[-1]]
    sizes, full = np.diff(ends), np.asarray(modes) == DENSE
    if full.all():
        return flat.reshape(n, spec.r)
    out = np.zeros((n, spec.r), np.uint8)
    of_full = np.repeat(full, sizes)
    out[full] = flat[of_full].reshape(-1, spec.r)
    entries = flat[~of_full].view(np.uint32)
    row = np.repeat(np.flatnonzero(~full), sizes[~full] // 4)
    out[row, entries >> np.uint32(8)] = (entries & np.uint32(255)).astype(np.uint8)
    return out


def _pack_rows(ids: np.ndarray, regs: np.ndarray, spec: SketchSpec, dense_only: bool) -> pa.RecordBatch:
    n, nz = len(ids), np.count_nonzero(regs, axis=1).astype(np.int32)
    if dense_only or (nz > spec.dense_at * spec.r).all():
        ends = np.arange(n + 1, dtype=np.int32) * np.int32(spec.r)
        data = pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(regs))])
        modes = np.full(n, DENSE, np.int8)
    else:
        packed = [to_bytes(j := np.flatnonzero(row), row[j], spec) for row in regs]
        modes, data = np.array([m for m, _ in packed], np.int8), pa.array([d for _, d in packed], pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(modes), data, pa.array(nz)], names=["x", "mode", "regs", "nz"])


def pack(regs: DataFrame, spec: SketchSpec, dense_only: bool = False) -> DataFrame:
    """x, mode, regs, nz from relational registers (a vertex has at most 2**p rows, so lists are bounded)."""
    lists = regs.groupBy("x").agg(F.collect_list((F.shiftleft("j", 8) + F.col("rho")).cast("int")).alias("e"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            modes, data, nz = [], [], []
            for e in batch.column(1):
                e = e.values.to_numpy()
                mode, raw = to_bytes(e >> 8, (e & 255).astype(np.uint8), spec, dense_only)
                modes.append(mode)
                data.append(raw)
                nz.append(len(e))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(modes, pa.int8()), pa.array(data, pa.binary()), pa.array(nz, pa.int32())], names=["x", "mode", "regs", "nz"])

    return lists.mapInArrow(run, SCHEMA)


def unpack(packed: DataFrame, spec: SketchSpec) -> DataFrame:
    """Relational registers x, j, rho."""

    def run(batches):
        for batch in batches:
            dense = to_dense(batch.column(1), batch.column(2), spec)
            row, j = np.nonzero(dense)
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(row)), pa.array(j.astype(np.int32)), pa.array(dense[row, j].astype(np.int32))], names=["x", "j", "rho"])

    return packed.select("x", "mode", "regs").mapInArrow(run, "x long, j int, rho int")


def merge_runs(rows: np.ndarray, at: np.ndarray) -> np.ndarray:
    """The column-wise maximum of each run of rows that starts at ``at`` (a run at a time: reduceat over rows is
    tens of times slower)."""
    out = np.array(rows[at])
    for i, (a, b) in enumerate(zip(at.tolist(), [*at[1:].tolist(), len(rows)], strict=True)):
        if b - a > 1:
            np.maximum.reduce(rows[a:b], axis=0, out=out[i])
    return out


def merge_packed(packed: DataFrame, spec: SketchSpec, dense_only: bool = False, salts: int = 1, held: int = 1 << 26) -> DataFrame:
    """One sketch for each x, the register-wise maximum of its rows, sparse and dense mixed.

    Each task merges before the shuffle in a table of at most ``held`` bytes, so an x leaves it about once, and a hub
    has about one row a task after the shuffle, which are merged as they come.  salts: over 1, each x is merged in
    so many parts first, for hubs whose rows fill the table again and again."""
    most = max(2, held // spec.r)

    def combine(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Merges rows with equal x; where the input is sorted by x, every x comes out once."""
        keys, regs, used, last = np.zeros(0, np.int64), np.zeros((0, spec.r), np.uint8), 0, 0
        place: dict[int, int] = {}

        def rows(keys: np.ndarray, regs: np.ndarray) -> Iterator[pa.RecordBatch]:
            for lo in range(0, len(keys), 4096):
                yield _pack_rows(keys[lo : lo + 4096], regs[lo : lo + 4096], spec, dense_only)

        for batch in batches:
            if not batch.num_rows:
                continue
            names = batch.schema.names
            order = np.argsort(np.asarray(batch.column(names.index("x"))), kind="stable")
            batch = batch.take(pa.array(order))
            ids, modes, data = (batch.column(names.index(c)) for c in ("x", "mode", "regs"))
            ids = np.asarray(ids)
            at = np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]])
            ends = np.r_[at[1:], len(ids)]
            for lo in range(0, len(at), 512):
                one = at[lo : lo + 512]
                span = slice(one[0], ends[min(lo + 511, len(at) - 1)])
                n = int(span.stop - span.start)
                fresh = merge_runs(to_dense(modes.slice(one[0], n), data.slice(one[0], n), spec), one - one[0])
                if used and used + len(one) > most:
                    # the last id may go on in the next rows: it stays
                    order = np.r_[0 : place[last], place[last] + 1 : used, place[last]]
                    keys, regs = keys[order], regs[order]
                    yield from rows(keys[:-1], regs[:-1])
                    keys, regs, place, used = keys[-1:], regs[-1:], {last: 0}, 1
                where = np.empty(len(one), np.int64)
                for i, x in enumerate(ids[one].tolist()):
                    where[i] = place.setdefault(x, len(place))
                if len(place) > len(keys):
                    grown = max(len(place), 2 * len(keys), 1024)
                    keys = np.r_[keys, np.zeros(grown - len(keys), np.int64)]
                    regs = np.vstack([regs, np.zeros((grown - len(regs), spec.r), np.uint8)])
                used = len(place)
                keys[where] = ids[one]
                regs[where] = np.maximum(regs[where], fresh)
                last = int(ids[one[-1]])
        yield from rows(keys[:used], regs[:used])

    part = packed.select("x", "mode", "regs").mapInArrow(combine, SCHEMA)
    if salts > 1:
        part = part.repartition(F.col("x"), F.pmod(F.xxhash64("regs"), F.lit(salts))).mapInArrow(combine, SCHEMA)
    return part.repartition("x").sortWithinPartitions("x").mapInArrow(combine, SCHEMA)


def measure_packed(packed: DataFrame, spec: SketchSpec, how: str = "beta", name: str = "n_est") -> DataFrame:
    def run(batches):
        for batch in batches:
            dense = to_dense(batch.column(1), batch.column(2), spec)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(estimate_array(dense, how))], names=["x", name])

    return packed.select("x", "mode", "regs").mapInArrow(run, f"x long, {name} double")


def ball_step_packed(layer: DataFrame, arcs: DataFrame, spec: SketchSpec, dense_only: bool = True) -> DataFrame:
    """One hop in packed form."""
    sent = arcs.join(layer, "x").select(F.col("y").alias("x"), "mode", "regs")
    return merge_packed(layer.select("x", "mode", "regs").unionByName(sent), spec, dense_only)
