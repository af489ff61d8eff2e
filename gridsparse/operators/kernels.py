"""Arrow kernels for the local product of one cell: outer products over common inner indices, and column by column."""

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from gridsparse.semiring import Semiring


def _arrays(table: pa.Table):
    return (table.column(c).to_numpy() for c in ("i", "j", "v"))


def _reduce(add: np.ufunc, i, j, v):
    """Sum entries of equal (i, j), in one sort of a joint key where it fits; fractions are added in the order given."""
    if not len(i):
        return i, j, v
    low, left = int(i.min()), int(j.min())
    height = int(i.max()) - low + 1
    if (int(j.max()) - left + 1) * height < 1 << 63:
        key = (j - left) * height + (i - low)
        order = np.argsort(key, kind=None if v.dtype.kind in "biu" else "stable")
        key = key[order]
        first = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
        at = order[first]
        return i[at], j[at], add.reduceat(v[order], first)
    order = np.lexsort((i, j))
    i, j, v = i[order], j[order], v[order]
    first = np.flatnonzero(np.concatenate(([True], (i[1:] != i[:-1]) | (j[1:] != j[:-1]))))
    return i[first], j[first], add.reduceat(v, first)


def outer(a: pa.Table, b: pa.Table, semiring: Semiring, most: int = 1 << 20):
    """Merge the outer products of A's columns and B's rows that share an inner index.

    Work and memory never depend on dimensions.  Products are made and reduced in
    chunks of about ``most``; pending chunks are merged into the result whenever
    they outgrow it, so memory follows the operands, the result and one chunk, and
    each product takes part in a number of merges that is logarithmic in the growth.
    """
    add, mul = (getattr(np, f) for f in semiring.ufunc)
    return _outer(*_arrays(a), _by_inner(*_arrays(b)), add, mul, most)


def _by_inner(k, j, v):
    """Entries sorted by inner index: the distinct indices, their first entry and number of entries, and the entries' j and v."""
    order = np.argsort(k, kind="stable")
    keys, first, number = np.unique(k[order], return_index=True, return_counts=True)
    return keys, first, number, j[order], v[order]


def _outer(ai, ak, av, by_inner, add: np.ufunc, mul: np.ufunc, most: int):
    rows, b0, bn, bj, bv = by_inner
    oa = np.argsort(ak, kind="stable")
    ai, ak, av = ai[oa], ak[oa], av[oa]
    columns, a0, an = np.unique(ak, return_index=True, return_counts=True)
    _, x, y = np.intersect1d(columns, rows, assume_unique=True, return_indices=True)
    sizes = an[x] * bn[y]
    done = [(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, av.dtype))]
    start, upto = 0, np.cumsum(sizes)
    while start < len(x):
        stop = max(start + 1, int(np.searchsorted(upto, (upto[start - 1] if start else 0) + most, side="right")))
        size = sizes[start:stop]
        at = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
        wide = np.repeat(bn[y[start:stop]], size)
        p = np.repeat(a0[x[start:stop]], size) + at // wide
        q = np.repeat(b0[y[start:stop]], size) + at % wide
        done.append(_reduce(add, ai[p], bj[q], mul(av[p], bv[q])))
        if sum(len(c[0]) for c in done[1:]) > max(most, len(done[0][0])):
            done = [_reduce(add, *(np.concatenate(c) for c in zip(*done, strict=True)))]
        start = stop
    return _reduce(add, *(np.concatenate(c) for c in zip(*done, strict=True)))


def _cuts(owner: np.ndarray, products: np.ndarray, most: int):
    """Runs of entries, sorted by ``owner``, of at most ``most`` products together; an owner is never cut."""
    edges = np.append(np.flatnonzero(np.concatenate(([True], owner[1:] != owner[:-1]))), len(owner)) if len(owner) else np.zeros(1, np.int64)
    upto = np.concatenate(([0], np.cumsum(products)))[edges]
    start = 0
    while start < len(edges) - 1:
        stop = max(start + 1, int(np.searchsorted(upto, upto[start] + most, side="right")) - 1)
        yield slice(edges[start], edges[stop])
        start = stop


def _matching(k: np.ndarray, keys: np.ndarray, number: np.ndarray) -> np.ndarray:
    """How many entries of the other operand each inner index meets."""
    if not len(keys):
        return np.zeros(len(k), np.int64)
    at = np.minimum(np.searchsorted(keys, k), len(keys) - 1)
    return np.where(keys[at] == k, number[at], 0)


def outer_runs(a, b, semiring: Semiring, most: int = 1 << 20):
    """``outer`` for one run of A's rows after another: disjoint parts of the result, each of about ``most`` products."""
    add, mul = (getattr(np, f) for f in semiring.ufunc)
    ai, ak, av = a
    by_inner = _by_inner(*b)
    order = np.argsort(ai, kind="stable")
    meets = _matching(ak, by_inner[0], by_inner[2])[order]
    order, meets = order[meets > 0], meets[meets > 0]
    ai, ak, av = ai[order], ak[order], av[order]
    for run in _cuts(ai, meets, most):
        yield _outer(ai[run], ak[run], av[run], by_inner, add, mul, most)


def columnwise_runs(a, b, semiring: Semiring, most: int = 1 << 20):
    """For each column of B, accumulate scaled columns of A in a dense vector over A's rows; some columns side by side, and a part of the result after each such run."""
    add, mul = (getattr(np, f) for f in semiring.ufunc)
    ai, ak, av = a
    bk, bj, bv = b
    names, rows = np.unique(ai, return_inverse=True)
    keys, first, number, rows, av = _by_inner(ak, rows, av)
    order = np.argsort(bj, kind="stable")
    meets = _matching(bk, keys, number)[order]
    order, meets = order[meets > 0], meets[meets > 0]
    bk, bj, bv = bk[order], bj[order], bv[order]
    if not len(bj):
        return
    wide = max(1, 4 * most // max(1, len(names)))  # columns whose vectors are held side by side
    place, dense = np.empty(wide * len(names), np.int64), None
    column = np.cumsum(np.concatenate(([0], bj[1:] != bj[:-1])))
    cut = np.flatnonzero(np.concatenate(([True], column[1:] // wide != column[:-1] // wide)))
    for low, high in zip(cut, [*cut[1:], len(column)], strict=True):
        for part in _cuts(bj[low:high], meets[low:high], most):
            run = slice(low + part.start, low + part.stop)
            size = meets[run]
            p = np.repeat(first[np.searchsorted(keys, bk[run])] - np.cumsum(size) + size, size) + np.arange(size.sum())
            value = mul(av[p], np.repeat(bv[run], size))
            cell = np.repeat(column[run] % wide, size) * len(names) + rows[p]
            if dense is None:
                dense = np.empty(len(place), value.dtype)
            every = np.arange(len(cell))
            place[cell[::-1]] = every[::-1]
            new = place[cell] == every
            dense[cell[new]] = value[new]
            add.at(dense, cell[~new], value[~new])
            found = np.sort(cell[new])
            yield names[found % len(names)], bj[run][np.searchsorted(column[run] % wide, found // len(names))], dense[found]


#: Side of a tile, and products in a pair of tiles from which a dense product of the two is cheaper than listing them.
TILE, DENSE_PRODUCTS = 512, 1 << 17


def _runs(keys: np.ndarray):
    """(key, slice) of each run of equal keys."""
    edges = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1]))) if len(keys) else np.empty(0, np.int64)
    return [(int(keys[low]), slice(low, high)) for low, high in zip(edges, [*edges[1:], len(keys)], strict=True)]


def _by_tile(x, y, v):
    """Entries by their tile: {tile of x: {tile of y: (x, y, v)}}, x and y within the tile."""
    order = np.lexsort((y // TILE, x // TILE))
    x, y, v = x[order], y[order], v[order]
    return {tx: {ty: (x[at][part] % TILE, y[at][part] % TILE, v[at][part]) for ty, part in _runs(y[at] // TILE)} for tx, at in _runs(x // TILE)}


def _filled(x, y, v, kind, rows: int | None = None, columns: int | None = None) -> np.ndarray:
    out = np.zeros((rows or TILE, columns or TILE), kind)
    out[x, y] = v
    return out


def exact_in_floats(a: np.ndarray, b: np.ndarray, inner: int) -> bool:
    """Whether sums of ``inner`` products are exact (whole numbers) or finite (others) in doubles, so that a dense product gives them."""
    if not len(a) or not len(b) or not all(x.dtype.kind in "iuf" for x in (a, b)):
        return False
    if a.dtype.kind == "f" or b.dtype.kind == "f":
        return bool(np.isfinite(a).all() and np.isfinite(b).all() and float(np.abs(a).max()) * float(np.abs(b).max()) * inner < 1e300)
    large = lambda x: max(abs(int(x.min())), abs(int(x.max())))
    return large(a) * large(b) * inner < 1 << 53


def tiled_runs(a, b, semiring: Semiring, most: int = 1 << 20):
    """Tile by tile of the result: dense products of pairs of tiles that have many, ``outer_runs`` over the rows of tiles that have few.

    Entries whose products cancel are kept, by a product of the patterns where values are not all positive.  Other semirings,
    and whole numbers whose sums might not be exact in doubles, take ``outer_runs``.
    """
    if semiring.ufunc != ("add", "multiply") or not exact_in_floats(a[2], b[2], min(len(a[0]), len(b[0]))):
        yield from outer_runs(a, b, semiring, most)
        return
    kind = np.result_type(a[2], b[2])
    positive = bool(a[2].min() > 0 and b[2].min() > 0) and kind.kind != "f"  # tiny products of fractions may round to 0
    keys, number = np.unique(b[0], return_counts=True)
    rows, right = _by_tile(*a), _by_tile(*b)
    for ti, left in rows.items():
        shared = [k for k in left if k in right]
        pairs = sum(len(right[k]) for k in shared)
        made = sum(int(_matching(left[k][1] + k * TILE, keys, number).sum()) for k in shared)
        if made < pairs * DENSE_PRODUCTS:
            if shared:
                strip = tuple(np.concatenate(c) for c in zip(*((left[k][0] + ti * TILE, left[k][1] + k * TILE, left[k][2]) for k in shared), strict=True))
                inner = tuple(np.concatenate(c) for c in zip(*((x + k * TILE, y + tj * TILE, w) for k in shared for tj, (x, y, w) in right[k].items()), strict=True))
                yield from outer_runs(strip, inner, semiring, most)
            continue
        wide = {k: 1 + max(int(left[k][1].max()), *(int(x.max()) for x, _, _ in right[k].values())) for k in shared}
        dense = {k: _filled(*left[k], np.float64, columns=wide[k]) for k in shared}
        for tj in sorted({t for k in shared for t in right[k]}):
            total, hits, full = np.zeros((TILE, TILE)), None, False
            for k in shared:
                if tj not in right[k]:
                    continue
                x, y, w = right[k][tj]
                total += dense[k] @ _filled(x, y, w, np.float64, wide[k])
                if not positive and not full:
                    found = _filled(left[k][0], left[k][1], 1, np.float32, columns=wide[k]) @ _filled(x, y, 1, np.float32, wide[k])
                    hits = found > 0 if hits is None else hits | (found > 0)
                    full = bool(hits.all())
            i, j = np.nonzero(total if positive else hits)
            yield i + ti * TILE, j + tj * TILE, (total[i, j] if kind.kind == "f" else np.rint(total[i, j])).astype(kind)


BATCH_ROWS = 100_000


def cell_kernel(kind: str, semiring: Semiring):
    """A group function for rows (right, k, x, v, w), entries of A as (x: i, k: inner, v) and of B as (k: inner, x: j, w), that yields i, j, v in bounded batches."""
    if semiring.ufunc is None:
        raise ValueError(f"{semiring.name} has no numpy form; use the relational kernel")
    body = {"outer": outer_runs, "columnwise": columnwise_runs, "tiled": tiled_runs}[kind]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sides = [], []
        for batch in batches:
            of_b = batch.column("right")
            for side, mask, columns in ((0, pc.invert(of_b), ("x", "k", "v")), (1, of_b, ("k", "x", "w"))):
                some = batch.filter(mask)
                if some.num_rows:
                    sides[side].append([some.column(c).to_numpy(zero_copy_only=False) for c in columns])
        if not sides[0] or not sides[1]:
            return
        a, b = (tuple(np.concatenate(c) for c in zip(*side, strict=True)) for side in sides)
        del sides
        for found in body(a, b, semiring):
            for at in range(0, len(found[0]), BATCH_ROWS):
                i, j, v = (c[at : at + BATCH_ROWS] for c in found)
                yield pa.RecordBatch.from_arrays([pa.array(i, pa.int64()), pa.array(j, pa.int64()), pa.array(v)], names=["i", "j", "v"])

    return run


#: A part of a tile of the result: the tile, positions in it (none: all, where 0 is no entry), the values' numpy type and the values.
PACKED = "ti long, tj long, at binary, kind string, v binary"
#: Inner indices that a packed strip is multiplied over at once.
INNER = 1024


def _narrowed(v: np.ndarray) -> np.ndarray:
    """Whole numbers in the narrowest of some types that holds them all."""
    if v.dtype.kind not in "iu" or not v.size:
        return v
    low, high = int(v.min()), int(v.max())
    return v.astype(next(t for t in (np.uint8, np.uint16, np.int16, np.int32, np.int64) if np.iinfo(t).min <= low and high <= np.iinfo(t).max))


def _listed_tiles(i, j, v, tile: int):
    """Distinct entries as packed parts with positions."""
    order = np.lexsort((j // tile, i // tile))
    i, j, v = i[order], j[order], v[order]
    ti, tj = i // tile, j // tile
    edges = np.flatnonzero(np.concatenate(([True], (ti[1:] != ti[:-1]) | (tj[1:] != tj[:-1])))) if len(i) else np.empty(0, np.int64)
    for low, high in zip(edges, [*edges[1:], len(i)], strict=True):
        part = slice(low, high)
        yield int(ti[low]), int(tj[low]), (i[part] % tile * tile + j[part] % tile).astype(np.uint32), _narrowed(v[part])


def packed_tiles(a, b, semiring: Semiring, tile: int = TILE, dense: bool = True):
    """The product as parts (tile of i, tile of j, positions or none, values), a strip of rows after another, by dense products over the inner indices of both.

    Single precision is taken where norms of rows and columns bound every sum below 2^24.  Values that doubles may not add, and
    all without ``dense``, are listed.
    """
    if not dense or semiring.ufunc != ("add", "multiply") or not exact_in_floats(a[2], b[2], min(len(a[0]), len(b[0]))):
        for run in outer_runs(a, b, semiring):
            yield from _listed_tiles(*run, tile)
        return
    keys = np.intersect1d(a[1], b[0])
    a, b = (tuple(c[np.isin(m[inner], keys)] for c in m) for m, inner in ((a, 1), (b, 0)))
    if not len(keys):
        return
    kind = np.result_type(a[2], b[2])
    positive = bool(a[2].min() > 0 and b[2].min() > 0) and kind.kind != "f"  # tiny products of fractions may round to 0
    columns, place = np.unique(b[1] // tile, return_inverse=True)
    place = place * tile + b[1] % tile
    of_b, wide = np.searchsorted(keys, b[0]), len(columns) * tile
    single = kind.kind != "f" and np.bincount(np.unique(a[0], return_inverse=True)[1], a[2].astype(float) ** 2).max() * np.bincount(place, b[2].astype(float) ** 2).max() < 2.0**47
    real = np.float32 if single else np.float64

    def right(low: int):
        some = (of_b >= low) & (of_b < low + INNER)
        return _filled(of_b[some] - low, place[some], b[2][some], real, min(INNER, len(keys) - low), wide)

    kept = right(0) if len(keys) <= INNER else None
    order = np.argsort(a[0] // tile, kind="stable")
    ai, ak, av = a[0][order], np.searchsorted(keys, a[1][order]), a[2][order]
    for ti, strip in _runs(ai // tile):
        total, hits = np.zeros((tile, wide), real), None if positive else np.zeros((tile, wide), bool)
        x, k, v = ai[strip] % tile, ak[strip], av[strip]
        for low in range(0, len(keys), INNER):
            some = (k >= low) & (k < low + INNER)
            inner, y = np.unique(k[some] - low, return_inverse=True)
            if not len(inner):
                continue
            block = right(low) if kept is None else kept
            block = block if len(inner) == len(block) else block[inner]
            total += _filled(x[some], y, v[some], real, tile, len(inner)) @ block
            if hits is not None:
                hits |= _filled(x[some], y, 1, np.float32, tile, len(inner)) @ (_pattern(of_b, place, low, len(keys), wide)[inner]) > 0
        for c, tj in enumerate(columns.tolist()):
            cells = slice(c * tile, (c + 1) * tile)
            found = total[:, cells].ravel() if kind.kind == "f" else np.rint(total[:, cells]).astype(np.int32 if single else kind).ravel()
            at = np.flatnonzero(found if hits is None else hits[:, cells])
            if not len(at):
                continue
            narrow = _narrowed(found)
            if hits is None and len(at) * (4 + narrow.itemsize) >= narrow.nbytes:
                yield ti, tj, None, narrow
            else:
                yield ti, tj, at.astype(np.uint32), narrow[at]


def _pattern(of_b: np.ndarray, place: np.ndarray, low: int, keys: int, wide: int) -> np.ndarray:
    some = (of_b >= low) & (of_b < low + INNER)
    return _filled(of_b[some] - low, place[some], 1, np.float32, min(INNER, keys - low), wide)


#: The entries of one strip of rows of A or columns of B in one slab: own indices x, inner indices k, values v, each with its numpy type.
STRIP = "slab int, strip int, xt string, x binary, kt string, k binary, vt string, v binary"


def strip_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A group function for rows (slab, strip, x, k, v) that yields the strip packed in one row."""
    held = list(batches)
    columns = [pa.array([held[0].column(c)[0].as_py()], pa.int32()) for c in ("slab", "strip")]
    for c in ("x", "k", "v"):
        values = _narrowed(np.concatenate([b.column(c).to_numpy(zero_copy_only=False) for b in held]))
        columns += [pa.array([values.dtype.str]), pa.array([values.tobytes()], pa.binary())]
    yield pa.RecordBatch.from_arrays(columns, names=["slab", "strip", "xt", "x", "kt", "k", "vt", "v"])


def strips_kernel(semiring: Semiring, *kinds: str):
    """A group function for packed strips (right, xt, x, kt, k, vt, v) of A and of B in a cell, ``kinds`` their values' types, that yields i, j, v by ``tiled_runs`` in bounded batches."""
    if semiring.ufunc is None:
        raise ValueError(f"{semiring.name} has no numpy form; use the relational kernel")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sides = {}
        for batch in batches:
            for row, of_b in enumerate(batch.column("right").to_pylist()):
                x, k, v = (np.frombuffer(batch.column(c)[row].as_buffer(), batch.column(c + "t")[row].as_py()) for c in ("x", "k", "v"))
                x, k, v = x.astype(np.int64), k.astype(np.int64), v.astype(np.int64 if kinds[of_b] == "bigint" else np.float64)
                sides[of_b] = (k, x, v) if of_b else (x, k, v)
        if len(sides) < 2:
            return
        for found in tiled_runs(sides[False], sides[True], semiring):
            for at in range(0, len(found[0]), BATCH_ROWS):
                i, j, v = (c[at : at + BATCH_ROWS] for c in found)
                yield pa.RecordBatch.from_arrays([pa.array(i, pa.int64()), pa.array(j, pa.int64()), pa.array(v)], names=["i", "j", "v"])

    return run


def packed_kernel(semiring: Semiring, tile: int, dense: bool):
    """A function for rows of a strip of A and one of B (columns of the latter end in b) that yields packed parts of tiles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                of = lambda c, end: np.frombuffer(batch.column(c + end)[row].as_buffer(), batch.column(c + "t" + end)[row].as_py())  # noqa: B023, E731
                a, b = ([of(c, end) for c in order] for end, order in (("", "xkv"), ("b", "kxv")))
                wide = lambda v: v if v.dtype.kind == "f" else v.astype(np.int64)
                for ti, tj, at, v in packed_tiles(tuple(map(wide, a)), tuple(map(wide, b)), semiring, tile, dense):
                    yield _packed_batch(ti, tj, at, v)

    return run


def _packed_batch(ti: int, tj: int, at: np.ndarray | None, v: np.ndarray) -> pa.RecordBatch:
    one = lambda x, t: pa.array([x], t)
    return pa.RecordBatch.from_arrays([one(ti, pa.int64()), one(tj, pa.int64()), one(None if at is None else at.tobytes(), pa.binary()), one(v.dtype.str, pa.string()), one(v.tobytes(), pa.binary())], names=["ti", "tj", "at", "kind", "v"])


def tile_kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A group function for the entries (i, j, v) of one tile that yields the tile packed in one row."""
    i, j, v = (np.concatenate(c) for c in zip(*(_arrays(b) for b in batches), strict=True))
    yield _packed_batch(int(i[0]) // TILE, int(j[0]) // TILE, (i % TILE * TILE + j % TILE).astype(np.uint32), _narrowed(v))


def copy_kernel(right: bool, own: dict[int, int], other: dict[int, list[int]], cells: dict[tuple[int, int], int]):
    """A function for packed tiles that yields a copy for each cell that needs it: of the left operand by strips of rows ``own`` and, by inner tile, strips of columns ``other``; of the right one the other way."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row, (ti, tj) in enumerate(zip(batch.column("ti").to_pylist(), batch.column("tj").to_pylist(), strict=True)):
                mine, inner = (own[tj], ti) if right else (own[ti], tj)
                for strip in other.get(inner, ()):
                    cell = cells[(strip, mine) if right else (mine, strip)]
                    yield pa.RecordBatch.from_arrays([pa.array([cell], pa.int32()), pa.array([right]), *batch.slice(row, 1).columns], names=["cell", "right", *batch.schema.names])

    return run


def _tile_dense(tile, kind) -> np.ndarray:
    at, v = tile
    if at is None:
        return v.reshape(TILE, TILE).astype(kind)
    out = np.zeros(TILE * TILE, kind)
    out[at] = v
    return out.reshape(TILE, TILE)


def _tile_pattern(tile) -> np.ndarray:
    at, v = tile
    return (v != 0).reshape(TILE, TILE) if at is None else _tile_dense((at, 1), bool)


def _tile_entries(tile, ti: int, tj: int, kind):
    at, v = tile
    place = np.flatnonzero(v) if at is None else at.astype(np.int64)
    return place // TILE + ti * TILE, place % TILE + tj * TILE, (v[place] if at is None else v).astype(kind)


def packed_products(left, right, semiring: Semiring, kind):
    """Parts (tile of i, tile of j, positions or none, values) of the product of packed tiles, {tile of i: {inner tile: (positions, values)}} times {inner tile: {tile of j: ...}}.

    A row of tiles is multiplied dense where pairs have many products, else listed, as by ``tiled_runs``; single precision is
    taken where it holds every sum.
    """
    kind = np.dtype(kind)
    tiles = [[v for row in x.values() for _, v in row.values() if len(v)] for x in (left, right)]
    if not all(tiles):
        return
    ends = [np.array([f(v) for v in x for f in (np.min, np.max)]).astype(kind) for x in tiles]
    positive = kind.kind != "f" and all(at is None or v.min() > 0 for x in (left, right) for row in x.values() for at, v in row.values() if len(v)) and all(v.min() >= 0 for x in tiles for v in x)
    degrees = {k: {tj: _tile_pattern(t).sum(axis=1) for tj, t in row.items()} for k, row in right.items()}
    for ti, row in left.items():
        shared = [k for k in row if k in right]
        if not shared:
            continue
        inner = len(shared) * TILE
        exact = semiring.ufunc == ("add", "multiply") and exact_in_floats(*ends, inner)
        meets = {k: _tile_pattern(row[k]).sum(axis=0) for k in shared}
        made = sum(int(meets[k] @ d) for k in shared for d in degrees[k].values())
        if not exact or made < sum(len(right[k]) for k in shared) * DENSE_PRODUCTS:
            a = tuple(np.concatenate(c) for c in zip(*(_tile_entries(row[k], ti, k, kind) for k in shared), strict=True))
            b = tuple(np.concatenate(c) for c in zip(*(_tile_entries(t, k, tj, kind) for k in shared for tj, t in right[k].items()), strict=True))
            parts: dict[int, list] = {}
            for run in outer_runs(a, b, semiring):
                for _, tj, at, v in _listed_tiles(*run, TILE):
                    parts.setdefault(tj, []).append((at, v))
            for tj, found in parts.items():  # runs have rows of their own: nothing to add
                yield ti, tj, *(np.concatenate(c) for c in zip(*found, strict=True))
            continue
        real = np.float32 if kind.kind != "f" and float(np.abs(ends[0]).max()) * float(np.abs(ends[1]).max()) * inner < 1 << 24 else np.float64
        for tj in sorted({t for k in shared for t in right[k]}):
            total, hits = np.zeros((TILE, TILE), real), None if positive else np.zeros((TILE, TILE), bool)
            for k in shared:
                if tj in right[k]:
                    total += _tile_dense(row[k], real) @ _tile_dense(right[k][tj], real)
                    if hits is not None and not hits.all():
                        hits |= _tile_pattern(row[k]).astype(np.float32) @ _tile_pattern(right[k][tj]).astype(np.float32) > 0
            found = total.ravel() if kind.kind == "f" else _narrowed(np.rint(total).astype(kind).ravel())
            at = np.flatnonzero(found if hits is None else hits)
            if hits is None and len(at) * (4 + found.itemsize) >= found.nbytes:
                yield ti, tj, None, found
            elif len(at):
                yield ti, tj, at.astype(np.uint32), found[at]


def product_kernel(semiring: Semiring, kind, packed: bool):
    """A group function for the packed tiles of a cell (right, ti, tj, at, kind, v) that yields their product, packed by tile or as rows i, j, v in bounded batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sides: tuple[dict, dict] = {}, {}
        for batch in batches:
            for of_b, ti, tj, at, name, blob in zip(*(batch.column(c) for c in ("right", "ti", "tj", "at", "kind", "v")), strict=True):
                tile = np.frombuffer(at.as_buffer(), np.uint32) if at.is_valid else None, np.frombuffer(blob.as_buffer(), name.as_py())
                sides[of_b.as_py()].setdefault(ti.as_py(), {})[tj.as_py()] = tile
        for ti, tj, at, v in packed_products(*sides, semiring, kind):
            if packed:
                yield _packed_batch(ti, tj, at, _narrowed(v))
                continue
            i, j, v = _tile_entries((at, v), ti, tj, kind)
            for low in range(0, len(i), BATCH_ROWS):
                yield pa.RecordBatch.from_arrays([pa.array(c[low : low + BATCH_ROWS]) for c in (i, j, v)], names=["i", "j", "v"])

    return run


def merge_kernel(tile: int, packed: bool):
    """A group function that adds the packed parts of one tile, to one packed part or to rows i, j, v in bounded batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = []
        for batch in batches:
            for ti, tj, at, kind, blob in zip(*(batch.column(c) for c in ("ti", "tj", "at", "kind", "v")), strict=True):
                row, column = ti.as_py(), tj.as_py()
                parts.append((np.frombuffer(at.as_buffer(), np.uint32) if at.is_valid else None, np.frombuffer(blob.as_buffer(), kind.as_py())))
        place, v = _added(parts, tile)
        if packed:
            yield _packed_batch(row, column, place.astype(np.uint32), _narrowed(v))
            return
        i, j = np.divmod(place, tile)
        for low in range(0, len(place), BATCH_ROWS):
            some = slice(low, low + BATCH_ROWS)
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in (i[some] + np.int64(row * tile), j[some] + np.int64(column * tile), v[some])], names=["i", "j", "v"])

    return run


def _added(parts: list[tuple[np.ndarray | None, np.ndarray]], tile: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions (signed) and sums of the parts of a tile; listed parts of a large tile are sorted, others added in an array of the tile."""
    kind = np.float64 if parts[0][1].dtype.kind == "f" else np.int64
    if all(at is not None for at, _ in parts) and tile > TILE:
        at, v = (np.concatenate(c) for c in zip(*((at.astype(np.int32 if tile <= 1 << 15 else np.int64), v.astype(kind)) for at, v in parts), strict=True))
        order = np.argsort(at, kind="stable")
        at, v = at[order], v[order]
        first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
        return at[first], np.add.reduceat(v, first)
    total, hits = np.zeros(tile * tile, kind), np.zeros(tile * tile, bool)
    for at, v in parts:
        if at is None:
            total += v
            hits |= v != 0
        else:
            total[at] += v
            hits[at] = True
    place = np.flatnonzero(hits).astype(np.int32)
    return place, total[place]
