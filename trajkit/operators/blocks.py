"""Items in blocks: a row holds some thousand items, their ids and their columns as compressed bytes.

A pass over plain rows spends most of its time on turning rows into columns and handing them to Python
(at 77 million items of twelve columns 54 s a pass, about a sixth of it in the kernel).  A table that
many passes read is packed once instead, so a pass hands over a few large byte strings.  Blocks hold
the same numbers, bit for bit.  The kernels here decide by matrix products where the margin is beyond
any rounding error, and leave every row in doubt to the kernels of ``lloyd``, so labels, captures and
counts are those of the plain way.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

VALUES = 1 << 15  # numbers a block, 256 KB
Chunk = tuple[pa.Array, np.ndarray]  # ids; columns times items


@dataclass
class Blocks:
    """``table``: n int, ids binary, x binary; ``id_type`` is the type of item_id."""

    table: DataFrame
    cols: list[str]
    id_type: str
    _items: list[int] = field(default_factory=list)

    def count(self) -> int:
        if not self._items:
            self._items.append(self.table.agg(F.sum("n").cast("long")).first()[0] or 0)
        return self._items[0]


def encoded(ids: pa.Array, x: np.ndarray) -> pa.RecordBatch:
    """One block; ``x`` has a row a column."""
    sink = pa.BufferOutputStream()
    options = pa.ipc.IpcWriteOptions(compression="lz4")
    batch = pa.RecordBatch.from_arrays([ids], ["item_id"])
    with pa.ipc.new_stream(sink, batch.schema, options=options) as out:
        out.write_batch(batch)
    body = pa.compress(np.ascontiguousarray(x, float), codec="lz4", asbytes=True)
    return pa.RecordBatch.from_arrays([pa.array([x.shape[1]], pa.int32()), pa.array([sink.getvalue().to_pybytes()], pa.binary()), pa.array([body], pa.binary())], ["n", "ids", "x"])


def ids_of(body: bytes) -> pa.Array:
    return pa.ipc.open_stream(body).read_all().column(0).combine_chunks()


def columns_of(body: bytes, n: int, width: int) -> np.ndarray:
    raw = pa.decompress(body, 8 * n * width, codec="lz4") if n else b""
    return np.frombuffer(raw, float).reshape(width, n)


def cut(ids: pa.Array, x: np.ndarray) -> Iterator[Chunk]:
    rows = max(1, VALUES // max(1, len(x)))
    for i in range(0, x.shape[1], rows):
        yield ids[i : i + rows], x[:, i : i + rows]


def source(z: DataFrame | Blocks, cols: list[str], ids: bool = True) -> tuple[DataFrame, Callable[[Iterator[pa.RecordBatch]], Iterator[Chunk]]]:
    """The table to map over and what makes chunks of its batches; without ``ids`` they are not read."""
    if isinstance(z, Blocks):
        if list(cols) != list(z.cols):
            raise ValueError("blocks hold other columns")

        def unpacked(batches: Iterator[pa.RecordBatch]) -> Iterator[Chunk]:
            for b in batches:
                for i in range(b.num_rows):
                    x = columns_of(b.column("x")[i].as_buffer(), b.column("n")[i].as_py(), len(cols))
                    yield (ids_of(b.column("ids")[i].as_buffer()) if ids else None), x

        return z.table.select(*(["n", "ids", "x"] if ids else ["n", "x"])), unpacked

    def plain(batches: Iterator[pa.RecordBatch]) -> Iterator[Chunk]:
        for b in batches:
            x = np.stack([b.column(c).to_numpy(zero_copy_only=False).astype(float, copy=False) for c in cols])
            yield from cut(b.column("item_id") if ids else pa.nulls(b.num_rows), x)

    return z.select(*(["item_id", *cols] if ids else cols)), plain


def packed(z: DataFrame | Blocks, cols: list[str], each: Callable[[pa.Array, np.ndarray], Chunk] | None = None) -> Blocks:
    """``z`` as blocks, stored; ``each`` makes new items of a chunk's, fewer or more."""
    from trajkit.sources.shared import materialised  # this module goes to workers by value, that one is not there

    if isinstance(z, Blocks) and each is None:
        return z
    table, chunks = source(z, cols)
    id_type = z.id_type if isinstance(z, Blocks) else z.schema["item_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[Chunk] = []
        rows = max(1, VALUES // max(1, len(cols)))

        def merged() -> pa.RecordBatch:
            return encoded(pa.concat_arrays([i for i, _ in held]), np.concatenate([x for _, x in held], axis=1))

        for chunk in chunks(batches):
            for ids, x in cut(*(each(*chunk) if each else chunk)):
                if held and sum(len(i) for i, _ in held) + len(ids) > rows:
                    yield merged()
                    held = []
                held.append((ids, x))
        if held:
            yield merged()

    return Blocks(materialised(table.mapInArrow(run, "n int, ids binary, x binary"), row_group=8 << 20), list(cols), id_type)


def copies(z: Blocks, times: int) -> Blocks:
    """Every item ``times`` times, under the ids item_id * times + 1 and so on."""

    def each(ids: pa.Array, x: np.ndarray) -> Chunk:
        names = np.repeat(ids.to_numpy(zero_copy_only=False) * times, times) + np.tile(np.arange(1, times + 1), len(ids))
        return pa.array(names, ids.type), np.repeat(x, times, axis=1)

    return packed(z, z.cols, each)


def shifted(x: np.ndarray, centers: np.ndarray) -> tuple[np.ndarray, float]:
    """Squared distances less the item's own square (centres times items), and a bound of their error."""
    square = (centers**2).sum(1)
    top = max(float(x.max()), -float(x.min())) if x.size else 0.0
    return square[:, None] - 2 * (centers @ x), 1e-12 * (len(x) * top**2 + float(square.max()) + 1)


def labels(x: np.ndarray, centers: np.ndarray, closest) -> np.ndarray:
    """Label of the nearest centre by rounded distance, the first of equals."""
    d, error = shifted(x, centers)
    label, best, second = np.zeros(x.shape[1], np.int32), d[0].copy(), np.full(x.shape[1], np.inf)
    for i in range(1, len(d)):
        less = d[i] < best
        np.minimum(second, np.maximum(d[i], best), out=second)
        np.minimum(best, d[i], out=best)
        label[less] = i
    # Distances more than one unit of the last digit apart cannot be rounded to the same number.
    doubt = np.flatnonzero(~(second - best > 1e-8 + 4 * error))
    if len(doubt) and len(d) > 1:
        label[doubt] = closest(x[:, doubt].T, centers)[0]
    return label


def within(x: np.ndarray, balls: np.ndarray, eps: float, closest) -> np.ndarray:
    """Whether the rounded distance to the nearest centre is at most ``eps``."""
    d, error = shifted(x, balls)
    d2 = d.min(0) + np.einsum("ij,ij->j", x, x)
    near = d2 <= eps**2
    doubt = np.flatnonzero(~(np.abs(d2 - eps**2) > 1e-8 + 4 * error))
    if len(doubt):
        near[doubt] = closest(x[:, doubt].T, balls)[1] <= eps**2
    return near


def exact_sums(x: np.ndarray, label: np.ndarray, k: int, digits: int, grid_sums) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``grid_sums`` by a product with the labels' indicators: whole numbers below 2^53 add without error."""
    v = x * 10.0**digits
    unit = np.rint(v)
    left = np.abs(v - unit)
    top = max(float(unit.max()), -float(unit.min())) if x.size else 0.0
    np.abs(v, out=v)
    v *= 2.0**-51
    if not (top * x.shape[1] < 2**53 and (left <= v).all()):
        return grid_sums(x.T, label, k)
    mark = (label == np.arange(k, dtype=label.dtype)[:, None]).astype(float)
    return mark.sum(1).astype(np.int64), (mark @ unit.T).astype(np.int64), np.zeros((k, len(x)))


def first_by_hash(z: Blocks, k: int, seed: str, first_vectors) -> np.ndarray:
    """The k different vectors whose items come first by hash.  A pass brings the first 16 k items;
    if most are copies, the next looks among items that differ from what is found."""
    cols, table, chunks = z.cols, *source(z, z.cols)
    most, found = 16 * k, np.zeros((0, len(z.cols)))
    while len(found) < k:
        known = {r.tobytes() for r in found}

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            best: list[tuple[bytes, bytes]] = []
            last = b"\xff" * 17
            for ids, x in chunks(batches):
                new = []
                for i, name in enumerate(ids.to_pylist()):
                    h = md5(f"{seed}|{name}".encode()).digest()
                    if h < last and name is not None:
                        v = (x[:, i] + 0.0).tobytes()  # no negative zero
                        if v not in known:  # noqa: B023
                            new.append((h, v))
                if new:
                    best = sorted(best + new)[:most]
                    last = best[-1][0] if len(best) == most else last
            yield pa.RecordBatch.from_arrays([pa.array([h for h, _ in best], pa.binary()), pa.array([v for _, v in best], pa.binary())], ["h", "v"])

        rows = table.mapInArrow(run, "h binary, v binary").orderBy("h").limit(most).collect()
        x = np.array([np.frombuffer(bytes(r["v"]), float) for r in rows]).reshape(-1, len(cols))
        found = np.concatenate([found, first_vectors([bytes(r["h"]) for r in rows], x, k - len(found))])
        if len(rows) < most:
            break
    return found
