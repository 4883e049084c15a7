"""Sum of a bag's product onto the variables it keeps, made prefix by prefix (M7f, M7g).

Two factors a(j, x) and b(j, y) meet in the variables j, which are summed out. Listing the bag and shuffling
its rows by (x, y) costs a row for each of its tuples. Here the bag stays factorised until the last step: a
tuple of j has a list of x and a list of y. The values of x are dealt to cells, and a cell gets, once for each
tuple of j, the list of y beside those x of the list that are its own. A cell thus has every tuple of the bag
with its values of x, and sums them a few prefixes x at a time. Lists travel as differences of sorted values.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import functions as F

from ..functions.semiring import SUM_PRODUCT, Semiring
from ..model import W, Factor
from .relational import materialise

#: Tuples of the bag in a cell, about; a cell's lists are no longer than that.
CELL_ROWS = 1 << 22
#: Tuples of the bag that a task lists at a time.
ROWS = 1 << 19
#: Bytes of lists that a task sends at a time.
SEND = 8 << 20

_INTEGERS = ("bigint", "int", "smallint", "tinyint")


def fits(factors: list[Factor], free: tuple[str, ...], semiring: Semiring = SUM_PRODUCT) -> bool:
    """Two factors that share just what is summed out, one integer variable beside it in each, and integer weights."""
    if semiring is not SUM_PRODUCT or len(factors) != 2:
        return False
    (a, b), kept = factors, set(free)
    own = [set(f.vars) & kept for f in factors]
    kinds = [dict(f.df.dtypes) for f in factors]
    return (
        set(a.vars) - kept == set(b.vars) - kept != set() and all(len(o) == 1 for o in own) and own[0] | own[1] == kept and len(kept) == 2
        and all(k[v] in _INTEGERS for k, o in zip(kinds, own) for v in o) and all(k[W] == "bigint" for k in kinds)
    )


def _narrow(low: int, high: int) -> np.dtype:
    return next(np.dtype(k) for k in (np.int8, np.int16, np.int32, np.int64) if np.iinfo(k).min <= low and high <= np.iinfo(k).max)


def pack(v: np.ndarray) -> bytes:
    """Integers in the fewest bytes that hold them all, by byte position, compressed; equal ones as one."""
    low, high = (int(v.min()), int(v.max())) if len(v) else (0, 0)
    if low == high:
        return struct.pack("<bqq", 0, len(v), low)
    kind = _narrow(low, high)
    raw = np.ascontiguousarray(v.astype(kind).view(np.uint8).reshape(-1, kind.itemsize).T).tobytes()
    out = pa.compress(raw, codec="zstd", asbytes=True)
    return struct.pack("<bqq", kind.itemsize, len(v), len(out)) + out


def unpack(data: bytes, n: int) -> list[np.ndarray]:
    """The ``n`` arrays that were packed one after the other, as narrow as they came."""
    out, at, head = [], 0, struct.calcsize("<bqq")
    for _ in range(n):
        width, size, length = struct.unpack_from("<bqq", data, at)
        at += head
        if not width:
            out.append(np.full(size, length, _narrow(length, length)))
            continue
        raw = pa.decompress(pa.py_buffer(data)[at : at + length], size * width, codec="zstd", asbytes=True)
        out.append(np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(width, -1).T).view(f"<i{width}").ravel())
        at += length
    return out


def starts(n: np.ndarray) -> np.ndarray:
    return np.cumsum(n) - n


def ranges(lo: np.ndarray, n: np.ndarray) -> np.ndarray:
    """lo[0], lo[0] + 1, ... (n[0] numbers), then those of the next."""
    return np.arange(int(n.sum())) + np.repeat(lo - starts(n), n)


def _lists(column: pa.ListArray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Lengths, values (0 for null), which are null, and weights."""
    v, w = column.flatten().flatten()
    n = pc.list_value_length(column).to_numpy(zero_copy_only=False).astype(np.int64)
    return n, pc.fill_null(v, 0).to_numpy(zero_copy_only=False), pc.is_null(v).to_numpy(zero_copy_only=False).astype(np.int64), w.to_numpy(zero_copy_only=False)


def _cells_of(v: np.ndarray, cells: int) -> np.ndarray:
    return ((v.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)).astype(np.int64) % cells


def _deal(cells: int):
    """(a list, b list) per tuple of what is summed out -> (cell, lists of many such tuples)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            na, va, zero_a, wa = _lists(batch.column("a"))
            nb, vb, zero_b, wb = _lists(batch.column("b"))
            if not len(va):
                continue
            order = np.lexsort((vb, np.repeat(np.arange(len(nb)), nb)))
            vb, zero_b, wb, at = vb[order], zero_b[order], wb[order], starts(nb)
            step = vb.copy()
            step[1:] -= vb[:-1]  # wraps where it must, as does the sum that undoes it
            step[at] = vb[at]
            cell, row = _cells_of(va, cells), np.repeat(np.arange(len(na)), na)
            order = np.argsort(cell, kind="stable")  # rows stay in their order
            cell, row, va, zero_a, wa = cell[order], row[order], va[order], zero_a[order], wa[order]
            cut = np.append(np.flatnonzero(np.append(True, cell[1:] != cell[:-1])), len(cell)).tolist()
            out, size = ([], []), 0
            for lo, hi in zip(cut, cut[1:]):
                own = row[lo:hi]
                first = np.flatnonzero(np.append(True, own[1:] != own[:-1]))
                tuples = own[first]
                pos = ranges(at[tuples], nb[tuples])
                parts = (np.diff(np.append(first, hi - lo)), va[lo:hi], zero_a[lo:hi], wa[lo:hi], nb[tuples], step[pos], zero_b[pos], wb[pos])
                out[0].append(int(cell[lo]))
                out[1].append(b"".join(map(pack, parts)))
                size += len(out[1][-1])
                if size >= SEND or hi == cut[-1]:
                    yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int32()), pa.array(out[1], pa.binary())], names=["cell", "lists"])
                    out, size = ([], []), 0

    return run


def _total(key: np.ndarray, w: np.ndarray | None, most: int, low: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys in order and the sum of their weights; ``w`` None: all one. ``low``, ``most``: bounds of the weights."""
    if w is None:
        key.sort()
    elif low >= 0 and (bits := most.bit_length()) + int(key.max()).bit_length() < 63:
        both = (key << bits) | w  # sorting one array is far cheaper than finding its order
        both.sort()
        key, w = both >> bits, both & ((1 << bits) - 1)
    else:
        order = np.argsort(key, kind="stable")
        key, w = key[order], w[order]
    first = np.flatnonzero(np.append(True, key[1:] != key[:-1]))
    if w is None:
        return key[first], np.diff(np.append(first, len(key)))
    if max(most, -low) * len(w) >= 1 << 63 and np.abs(np.add.reduceat(w.astype(np.float64), first)).max() >= 2.0**63:
        raise OverflowError("a sum of weights exceeds a bigint")
    return key[first], np.add.reduceat(w, first)


def sums_of_cell(lists: list[bytes], rows: int = ROWS) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(x, is x null, y, is y null, sum) of one cell, x by x, about ``rows`` tuples of the bag at a time."""
    na, va, zero_a, wa, nb, step, zero_b, wb = (np.concatenate(p) for p in zip(*(unpack(x, 8) for x in lists)))
    na, va, wa, nb = (v.astype(np.int64) for v in (na, va, wa, nb))  # the others are long and stay narrow
    at = starts(nb)
    vb = np.cumsum(step, dtype=np.int64)
    vb -= np.repeat(vb[at] - step[at], nb)
    low = int(vb.min())
    span = int(vb.max()) - low + 1  # the code of null, if there is one
    names = None
    if span.bit_length() + len(va).bit_length() < 62:
        vb -= low
    else:
        names, vb = np.unique(vb, return_inverse=True)
        span = len(names)
    code = vb.astype(np.int32 if span < 1 << 31 else np.int64)
    code[zero_b == 1] = span
    del vb, step, zero_b
    ybits = span.bit_length()
    ones = bool((wa == 1).all() and (wb == 1).all())
    ends = [int(p) * int(q) for p in (wa.min(), wa.max()) for q in (wb.min(), wb.max())]
    if max(map(abs, ends)) >= 1 << 63:
        raise OverflowError("a product of weights exceeds a bigint")

    row = np.repeat(np.arange(len(na)), na)
    order = np.lexsort((va, zero_a))
    va, zero_a, wa, row = va[order], zero_a[order], wa[order], row[order]
    new = np.append(True, (va[1:] != va[:-1]) | (zero_a[1:] != zero_a[:-1]))
    group, first = np.cumsum(new) - 1, np.flatnonzero(new)
    x, zero_x = va[first], zero_a[first]
    n = nb[row]
    done = np.cumsum(n)
    bound = np.append(first, len(va))  # where the groups begin, and the end

    def listed(lo: int, hi: int) -> tuple[np.ndarray, np.ndarray]:
        m = n[lo:hi]
        pos = ranges(at[row[lo:hi]], m)
        key = np.repeat(group[lo:hi] << ybits, m) | code[pos]
        return _total(key, None if ones else np.repeat(wa[lo:hi], m) * wb[pos], max(ends), min(ends))

    def cuts(lo: int, hi: int) -> Iterator[tuple[int, int]]:
        while lo < hi:
            to = min(hi, max(lo + 1, int(np.searchsorted(done, (int(done[lo - 1]) if lo else 0) + rows, "right"))))
            yield lo, to
            lo = to

    g = 0
    while g < len(first):
        lo = int(bound[g])
        to = int(np.searchsorted(done, (int(done[lo - 1]) if lo else 0) + rows, "right"))
        h = max(g + 1, int(np.searchsorted(bound, to, "right")) - 1)  # whole groups; one alone may be longer
        key, w = None, None
        for p, q in cuts(lo, int(bound[h])):
            k, s = listed(p, q)
            if key is not None:
                k, s = np.concatenate([key, k]), np.concatenate([w, s])
                k, s = _total(k, s, int(s.max()), int(s.min()))
            key, w = k, s
        who, y = key >> ybits, key & ((1 << ybits) - 1)
        zero_y = y == span
        y = y + low if names is None else names[np.minimum(y, span - 1)]
        yield x[who], zero_x[who] == 1, y, zero_y, w
        g = h


def _solve(names: list[str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lists = [x for batch in batches for x in batch.column("lists").to_pylist()]
        for x, zero_x, y, zero_y, w in sums_of_cell(lists) if lists else ():
            cols = [pa.array(v, mask=zero if zero.any() else None) for v, zero in ((x, zero_x), (y, zero_y))]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(w)], names=names)

    return run


def summed_product(factors: list[Factor], free: tuple[str, ...], domains: dict[str, int] | None = None) -> Factor:
    """The product of two factors that ``fits`` allows, summed onto ``free``; rows with a null in what is summed out meet none."""
    spark = factors[0].df.sparkSession
    on = [v for v in factors[0].vars if v not in free]
    a, b = sorted(factors, key=lambda f: -max((domains or {}).get(v, 0) for v in f.vars if v in free))  # the finer variable is dealt
    (x,), (y,) = ([v for v in f.vars if v in free] for f in (a, b))
    sides = [f.df.groupBy(*on).agg(F.collect_list(F.struct(F.col(v).cast("bigint").alias("v"), F.col(W).alias("w"))).alias(to)) for f, v, to in ((a, x, "a"), (b, y, "b"))]
    lists = materialise(sides[0].join(sides[1], on).select("a", "b"))
    rows = lists.agg(F.sum(F.size("a").cast("bigint") * F.size("b"))).first()[0] or 0
    cells = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-rows // CELL_ROWS))
    dealt = lists.mapInArrow(_deal(cells), "cell int, lists binary").repartitionById(cells, F.col("cell"))
    out = dealt.mapInArrow(_solve([x, y, W]), f"`{x}` bigint, `{y}` bigint, {W} bigint")
    kinds = {x: dict(a.df.dtypes)[x], y: dict(b.df.dtypes)[y]}
    return Factor("bag", tuple(free), out.select(*[F.col(v).cast(kinds[v]).alias(v) for v in free], W))
