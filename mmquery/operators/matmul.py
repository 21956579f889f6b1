"""Boolean and counting products of relations seen as matrices."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import IntegerType, LongType, StringType, StructField, StructType

from ..sources.tables import cut

#: Side of a square block, in values.
SIDE = 2048
#: Rows of a band; rows from which a small relation has more than one, and bands that it gets then at most.
TILE_ROWS, LEAST_ROWS, FEW_BANDS = 2_000_000, 20_000, 4
#: Pairs of rows that are sorted at a time, rows of a batch, and tasks of a product.
CHUNK, BATCH, MOST_TASKS = 1_000_000, 100_000, 10_000
CUTOFF = 64


@dataclass(frozen=True)
class Kernel:
    """A way to multiply dense 0/1 blocks, with the exponent it stands for, the type it works on and about what it takes for a multiplication in ns.

    `meets` is a cheaper product for where only the pairs are asked for.
    """

    name: str
    omega: Fraction
    multiply: Callable[[np.ndarray, np.ndarray], np.ndarray]
    counts: bool
    dtype: type = np.int8
    price: float = 0.03
    meets: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None


def _blas(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return a.astype(np.float32, copy=False) @ b.astype(np.float32, copy=False)


def _bitset(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Rows and columns as words; a pair is set where any word has a common bit."""
    left, right = np.packbits(a.astype(bool), axis=1), np.packbits(b.T.astype(bool), axis=1)
    pad = -left.shape[1] % 8
    left, right = (np.ascontiguousarray(np.pad(x, ((0, 0), (0, pad)))).view(np.uint64) for x in (left, right))
    out = np.zeros((len(left), len(right)), np.int64)
    for i, row in enumerate(left):
        some = np.flatnonzero(row)
        if len(some):
            out[i] = np.bitwise_count(right[:, some] & row[some]).sum(1)
    return out


def _bitset_meets(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The columns of an inner value as words; a row is the or of its inner values'."""
    words = np.packbits(b, axis=1)
    if words.shape[1] % 8:
        words = np.pad(words, ((0, 0), (0, -words.shape[1] % 8)))
    words = words.view(np.uint64)
    out = np.zeros((len(a), words.shape[1]), np.uint64)
    i, k = np.nonzero(a)
    ends = np.searchsorted(i, np.arange(len(a) + 1))
    for row, lo, hi in zip(out, ends[:-1], ends[1:], strict=True):
        np.bitwise_or.reduce(words[k[lo:hi]], axis=0, out=row)
    return np.unpackbits(out.view(np.uint8), axis=1, count=b.shape[1]).view(bool)


def _recursive(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Seven half-size products in place of eight, until a dimension is down to a cutoff; the public textbook identities."""

    def even(x: np.ndarray) -> np.ndarray:
        return np.pad(x, [(0, n % 2) for n in x.shape]) if any(n % 2 for n in x.shape) else x

    def go(p: np.ndarray, q: np.ndarray) -> np.ndarray:
        if min(*p.shape, q.shape[1]) <= CUTOFF:
            return p @ q
        m, n = len(p), q.shape[1]
        p, q = even(p), even(q)
        i, k, j = len(p) // 2, len(q) // 2, q.shape[1] // 2
        (p1, p2), (p3, p4) = (p[:i, :k], p[:i, k:]), (p[i:, :k], p[i:, k:])
        (q1, q2), (q3, q4) = (q[:k, :j], q[:k, j:]), (q[k:, :j], q[k:, j:])
        diagonal = go(p1 + p4, q1 + q4)
        low, high = go(p3 + p4, q1), go(p1, q2 - q4)
        turn, wide = go(p4, q3 - q1), go(p1 + p2, q4)
        first, last = go(p3 - p1, q1 + q2), go(p2 - p4, q3 + q4)
        out = np.empty((2 * i, 2 * j))
        out[:i, :j] = diagonal + turn - wide + last
        out[:i, j:] = high + wide
        out[i:, :j] = low + turn
        out[i:, j:] = diagonal - low + high + first
        return out[:m, :n]

    return np.ascontiguousarray(go(a.astype(np.float64, copy=False), b.astype(np.float64, copy=False)))


KERNELS = {
    "blas": Kernel("blas", Fraction(3), _blas, True, np.float32),
    "bitset": Kernel("bitset", Fraction(3), _bitset, True, np.int8, 0.02, _bitset_meets),
    "recursive7": Kernel("recursive7", Fraction(281, 100), _recursive, True, np.float64, 0.06),
}
#: What a block takes besides its multiplications, in ns: each, a value of its right matrix, a value of its product.
BLOCK_NS, RIGHT_NS, OUT_NS = 200_000, 0.1, 1.0
#: Blocks of the same number of rows, until it is looked at again.
SAME = 6
#: Right matrices with a one in so many values at least are multiplied in square pieces, sparser ones are packed.
THIN = 32


def fuse(df: DataFrame, columns: list[str], name: str) -> DataFrame:
    """Several variables as one index."""
    return df.withColumn(name, F.struct(*columns)).drop(*columns)


def mm_sparse(r: DataFrame, s: DataFrame, inner: list[str], group: list[str] | None = None, count: bool = False, tiles: bool = False) -> DataFrame:
    """Pairs of the outer columns that share an inner value (within a group): a join and a distinct, or their number `n`.

    With `tiles`, both are done in tiles of the product, for products with far more pairs than rows: no pair is ever shuffled.
    """
    group = group or []
    if tiles:
        return _tiled(r, s, inner, group, None, SIDE, count)
    joined = r.join(s, [*group, *inner]).drop(*inner)
    if count:
        return joined.groupBy(*joined.columns).agg(F.count("*").alias("n"))
    return joined.distinct()


def mm_blocked(r: DataFrame, s: DataFrame, inner: list[str], group: list[str] | None = None, kernel: str = "blas", side: int | None = None, count: bool = False, per_row: dict[str, str] | None = None) -> DataFrame:
    """The same product in blocks of dense values, `side` rows and side * side values of a matrix at most, for each value of the group's columns.

    With `per_row`, a left value's pairs are summed up within their tile: long columns by name that are its `pairs` (how many), `paths` (the sum
    of their counts), `most` (the greatest count) or the sum of an integral right column. A left value has some such rows, to be summed (or `most` compared).
    """
    return _tiled(r, s, inner, group or [], kernel, side or SIDE, count, per_row=per_row)


def mm_total(r: DataFrame, s: DataFrame, at: DataFrame, inner: list[str], kernel: str = "blas", side: int | None = None) -> DataFrame:
    """The counting product summed at the pairs of outer values that `at` holds, as one row `n`.

    A pair of `at` goes to its tile, so no pair of the product leaves it, and only rows and columns that `at` asks for are multiplied.
    """
    return _tiled(r, s, inner, [], kernel, side or SIDE, True, at).agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def _tiled(r: DataFrame, s: DataFrame, inner: list[str], group: list[str], kernel: str | None, side: int, count: bool, at: DataFrame | None = None, per_row: dict[str, str] | None = None) -> DataFrame:
    """Tiles of the product: the rows of r are hashed by their outer values to bands, so are those of s; a task holds a band of each, whole in the inner dimension.

    A pair lies in one tile, so nothing is reduced across tasks. The values of an inner value travel as one list; bands have about
    TILE_ROWS rows, so lists are repeated once for each band of the other side. With pairs `at`, the rows are sums of counts at them, and with
    `per_row` they are sums over the pairs of a left value.
    """
    left = [c for c in r.columns if c not in (*inner, *group)]
    right = [c for c in s.columns if c not in (*inner, *group)]
    on = [*group, *inner]
    (n_i, plain_l), (n_j, plain_r) = _bands(r, [*group, *left] if at is None else []), _bands(s, right if at is None else [])
    n = {"i": n_i, "j": n_j}

    def band_of(cols: list[str], salt: int, d: str):
        return F.pmod(F.xxhash64(*cols, F.lit(salt)), F.lit(n[d])).cast("int")

    def lists(df: DataFrame, cols: list[str], salt: int, d: str, other: str, name: str) -> DataFrame:
        band = band_of(cols, salt, d)
        plain = plain_l if d == "i" else plain_r
        entry = F.col(plain) if plain else F.struct(*cols) if cols else F.struct(F.lit(0).alias("__one"))
        out = df.dropna(subset=on).select(F.struct(*on).alias("__k"), band.alias(f"__{d}"), entry.alias("__v")).groupBy("__k", f"__{d}").agg(F.collect_set("__v").alias(name))
        out = out.withColumn(f"__{other}", F.explode(F.sequence(F.lit(0), F.lit(n[other] - 1))))
        return out.select((F.col("__i") * n["j"] + F.col("__j")).cast("int").alias("__t"), F.lit(0 if d == "i" else 1).alias("__side"), "__k", name)

    a, b = lists(r, [*group, *left], 1, "i", "j", "__l"), lists(s, right, 3, "j", "i", "__r")
    fields = [r.schema[c] for c in (*group, *left)] + [s.schema[c] for c in right if not per_row]
    summed = at is not None
    counts = count or bool({"paths", "most"} & set((per_row or {}).values()))
    schema = StructType([*([] if summed else fields), *(StructField(c, LongType()) for c in per_row or (["n"] if count else []))])
    arrow = to_arrow_schema(schema)
    names = [f.name for f in schema]

    def total(x: list[pa.RecordBatch], y: list[pa.RecordBatch], z: list[pa.RecordBatch]):
        (kx, ky), _ = _codes([_fields(x, "__k"), _fields(y, "__k")], on)
        rows, kx = _entries(x, "__l", kx)
        cols, ky = _entries(y, "__r", ky)
        first, list_of = _entries(z, "__l", np.arange(sum(len(b) for b in z)))
        second, list_of = _entries(z, "__r", list_of)
        (ri, mi), _ = _codes([rows, first.take(pa.array(list_of))], left)
        (cj, mj), _ = _codes([cols, second], right)
        yield from pa.table([pa.array([_dense_at(KERNELS[kernel].multiply, ri, kx, ky, cj, mi, mj, side)])], names=names).cast(arrow).to_batches()

    def product(x: list[pa.RecordBatch], y: list[pa.RecordBatch]):
        (kx, ky), _ = _codes([_fields(x, "__k"), _fields(y, "__k")], on)
        rows, kx = _entries(x, "__l", kx, plain_l)
        cols, ky = _entries(y, "__r", ky, plain_r)
        some = np.isin(kx, ky)
        rows, kx = rows.filter(pa.array(some)), kx[some]
        if not len(kx):
            return
        (ri,), row_at = _codes([rows], [*group, *left])
        (cj,), col_at = _codes([cols], right)
        found = _sparse(ri, kx, ky, cj, len(col_at)) if kernel is None else _dense(KERNELS[kernel], ri, kx, ky, cj, side, counts)
        of_row = [rows[c].take(pa.array(row_at)).combine_chunks() for c in (*group, *left)]
        of_col = {c: cols[c].take(pa.array(col_at)).combine_chunks() for c in right}
        if per_row:
            summed_up = {c: _integers(of_col[c]) for c in per_row.values() if c in right}
            found = (_per_row(*some, per_row, summed_up) for some in _gathered(found))
        for i, *others in _gathered(found):
            values = [v.take(pa.array(i)) for v in of_row]
            if per_row:
                values += [pa.array(v) for v in others]
            else:
                values += [v.take(pa.array(others[0])) for v in of_col.values()] + ([pa.array(others[1])] if count else [])
            yield from pa.table(values, names=names).cast(arrow).combine_chunks().to_batches(max_chunksize=BATCH)

    def work(batches):
        now, parts = None, ([], [], [])

        def done():
            x, y, z = parts
            if x and y and not summed:
                yield from product(x, y)
            elif x and y and z:
                yield from total(x, y, z)

        for batch in batches:
            t = batch["__t"].to_numpy(zero_copy_only=False)
            cuts = np.flatnonzero(np.diff(t)) + 1
            for lo, hi in zip([0, *cuts], [*cuts, len(t)], strict=True):
                if lo == hi:
                    continue
                if t[lo] != now:
                    yield from done()
                    now, parts = t[lo], ([], [], [])
                part = batch.slice(lo, hi - lo)
                ends = np.searchsorted(part["__side"].to_numpy(zero_copy_only=False), range(4))
                for rows, begin, end in zip(parts, ends[:-1], ends[1:], strict=True):
                    if begin < end:
                        rows.append(part.slice(begin, end - begin))
        yield from done()

    tiles = n["i"] * n["j"]
    dealt = a.unionByName(b, allowMissingColumns=True)
    if summed:
        tile = (band_of(left, 1, "i") * n["j"] + band_of(right, 3, "j")).cast("int")
        pairs = at.select(tile.alias("__t"), F.struct(*left).alias("__one"), F.struct(*right).alias("__v")).groupBy("__t", "__one").agg(F.collect_set("__v").alias("__r"))
        dealt = dealt.unionByName(pairs.select("__t", F.lit(2).alias("__side"), F.array("__one").alias("__l"), "__r"), allowMissingColumns=True)
    dealt = dealt.repartition(min(4 * tiles, MOST_TASKS) if tiles > 1 else 1, "__t").sortWithinPartitions("__t", "__side", "__k")
    return dealt.mapInArrow(work, schema)


def _bands(df: DataFrame, cols: list[str]) -> tuple[int, str | None]:
    """Bands of about TILE_ROWS rows; small relations get a few more, so that tasks share the work. Beside them the only one of the columns, if it's plain and never null."""
    one = cols[0] if len(cols) == 1 and isinstance(df.schema[cols[0]].dataType, (LongType, IntegerType, StringType)) else None
    rows, nulls = df.agg(F.count("*"), F.count_if(F.col(one).isNull()) if one else F.lit(0)).first()
    return max(1, -(-rows // TILE_ROWS), min(FEW_BANDS, rows // LEAST_ROWS)), one if not nulls else None


def _fields(batches: list[pa.RecordBatch], name: str) -> pa.Table:
    """The fields of a struct column."""
    return pa.table({f.name: pa.chunked_array([b[name].field(i) for b in batches]) for i, f in enumerate(batches[0][name].type)})


def _entries(batches: list[pa.RecordBatch], name: str, k: np.ndarray, plain: str | None = None) -> tuple[pa.Table, np.ndarray]:
    """The values of all lists as a table, and the inner value's number of each; lists of structs, or of the plain column."""
    lists = pa.chunked_array([b[name] for b in batches])
    flat = [c.flatten() for c in lists.chunks]
    many = np.concatenate([c.value_lengths().to_numpy(zero_copy_only=False) for c in lists.chunks]).astype(np.int64)
    fields = {plain: flat} if plain else {f.name: [c.field(i) for c in flat] for i, f in enumerate(flat[0].type)}
    return pa.table({c: pa.chunked_array(v) for c, v in fields.items()}), np.repeat(k, many)


def _gathered(found):
    """Arrays that come a few rows at a time, about a batch at a time."""
    parts, many = [], 0
    for part in found:
        parts.append(part)
        many += len(part[0])
        if many >= BATCH:
            yield tuple(np.concatenate(x) for x in zip(*parts, strict=True))
            parts, many = [], 0
    if many:
        yield tuple(np.concatenate(x) for x in zip(*parts, strict=True))


def _integers(values: pa.Array) -> np.ndarray:
    """Integers to be summed, nulls as 0."""
    return values.cast(pa.int64()).fill_null(0).to_numpy(zero_copy_only=False)


def _per_row(i: np.ndarray, j: np.ndarray, number: np.ndarray, per_row: dict[str, str], of_col: dict[str, np.ndarray]) -> tuple[np.ndarray, ...]:
    """The measures of each run of equal i, as mm_blocked() names them."""
    first = np.flatnonzero(np.diff(i, prepend=-1))
    out = []
    for what in per_row.values():
        if what in of_col:
            value = of_col[what][j]
            if len(value) and float(max(-int(value.min()), int(value.max()))) * len(value) >= 2**63 and np.abs(np.add.reduceat(value.astype(np.float64), first)).max() >= 2**63:
                raise OverflowError(f"the sum of {what} exceeds a long")
            out.append(np.add.reduceat(value, first))
        elif what == "pairs":
            out.append(np.diff(np.append(first, len(i))))
        else:
            out.append((np.add if what == "paths" else np.maximum).reduceat(number, first).astype(np.int64))
    return i[first], *out


def _sparse(ri: np.ndarray, kx: np.ndarray, ky: np.ndarray, cj: np.ndarray, width: int):
    """Pairs and their counts, some rows at a time: the columns of a row's inner values end to end, then sorted."""
    order = np.argsort(ri, kind="stable")
    ri, kx = ri[order], kx[order]
    by = np.argsort(ky, kind="stable")
    ky, cj = ky[by], cj[by]
    begin, end = np.searchsorted(ky, kx), np.searchsorted(ky, kx, "right")
    many = np.cumsum(end - begin)
    rows = np.append(np.flatnonzero(np.diff(ri, prepend=-1)), len(ri))
    at = 0
    while at < len(rows) - 1:
        lo = rows[at]
        before = many[lo - 1] if lo else 0
        # rows up to CHUNK pairs, one at least
        nxt = max(at + 1, int(np.searchsorted(many[rows[1:] - 1], before + CHUNK, "right")))
        hi = rows[nxt]
        length = (end - begin)[lo:hi]
        first = np.repeat(begin[lo:hi] - (np.cumsum(length) - length), length)
        pair = np.repeat(ri[lo:hi], length) * width + cj[first + np.arange(length.sum())]
        pair.sort()
        new = np.flatnonzero(np.diff(pair, prepend=-1))
        number = np.diff(np.append(new, len(pair)))
        pair = pair[new]
        i = pair // width
        yield i, pair - i * width, number
        at = nxt


def _dense(kernel: Kernel, ri: np.ndarray, kx: np.ndarray, ky: np.ndarray, cj: np.ndarray, side: int, count: bool):
    """Pairs and their counts, a packed block at a time: some rows, the inner values that they have, and the columns that those meet.

    Rows follow each other by their least inner value, `side` at most in a block: as many as make a pair cheapest. Few rows share few
    columns, so their block has few values for each one in it; rows that share most of theirs make large blocks.
    """
    multiply = kernel.multiply if count or not kernel.meets else kernel.meets
    n = int(ri.max()) + 1
    least = np.full(n, np.iinfo(np.int64).max)
    np.minimum.at(least, ri, kx)
    place = np.empty(n, np.int64)
    name = np.argsort(least, kind="stable")
    place[name] = np.arange(n)
    order = np.argsort(place[ri], kind="stable")
    ri, kx = place[ri][order], kx[order]
    start = np.searchsorted(ri, np.arange(n + 1))
    by = np.argsort(ky, kind="stable")
    ky, cj = ky[by], cj[by]
    begin = np.searchsorted(ky, np.arange(int(kx.max()) + 2))
    degree = np.diff(begin)
    paths = np.concatenate([[0], np.cumsum(degree[kx])])[start]
    width, most = int(cj.max()) + 1, side * side
    slot, slot_of_inner = np.empty(width, np.int64), np.empty(len(degree), np.int64)
    right = np.zeros(most + 64 * side, kernel.dtype)  # all 0 between blocks

    def distinct(values: np.ndarray, slot: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The distinct values, in any order, and the place of each value among them."""
        every = np.arange(len(values))
        slot[values] = every
        one = slot[values]
        new = one == every
        return values[new], (np.cumsum(new) - 1)[one]

    def price(ilo: int, size: int) -> float:
        """About what a pair takes in a block of so many rows."""
        ihi = min(ilo + size, n)
        lo, hi = start[ilo], start[ihi]
        inner = distinct(kx[lo:hi], slot_of_inner)[0]
        cols = -width * np.expm1(-degree[inner].sum() / width)
        work = (hi - lo if multiply is kernel.meets else (ihi - ilo) * len(inner)) * kernel.price
        return (BLOCK_NS + cols * (work + RIGHT_NS * len(inner) + OUT_NS * (ihi - ilo))) / (paths[ihi] - paths[ilo])

    def packed(ilo: int, ihi: int, r: np.ndarray, k: np.ndarray, inner: np.ndarray):
        """The block of inner values: its rows are known, its columns are those that the inner values have."""
        many = degree[inner]
        k2 = np.repeat(np.arange(len(inner)), many)
        met, code = distinct(cj[np.arange(len(k2)) + np.repeat(begin[inner] - (np.cumsum(many) - many), many)], slot)
        m1 = np.zeros((ihi - ilo, len(inner)), kernel.dtype)
        m1[r, k] = 1
        step = max(1, most // (ihi - ilo))
        for jlo in range(0, len(met), step):
            here = slice(None) if step >= len(met) else (code >= jlo) & (code < jlo + step)
            w = -(-min(step, len(met) - jlo) // 64) * 64
            ones = k2[here] * w + (code[here] - jlo)
            values = len(inner) * w
            m2 = right[:values] if values <= len(right) else np.zeros(values, kernel.dtype)
            m2[ones] = 1
            out = multiply(m1, m2.reshape(len(inner), w)).ravel()
            m2[ones] = 0
            flat = np.flatnonzero(out != 0)
            ends = np.searchsorted(flat, np.arange(ihi - ilo + 1) * w)
            many = np.diff(ends)
            yield np.repeat(name[ilo:ihi], many), met[flat - np.repeat(np.arange(ihi - ilo) * w - jlo, many)], out[flat]

    def square(ilo: int, ihi: int, inner: np.ndarray):
        lo, hi = start[ilo], start[ihi]
        many = degree[inner]
        at = np.repeat(begin[inner] - (np.cumsum(many) - many), many) + np.arange(many.sum())
        met, code = np.unique(cj[at], return_inverse=True)
        by_col = np.argsort(code, kind="stable")
        kc, code = ky[at][by_col], code[by_col]
        for jlo in range(0, len(met), side):
            clo, chi = np.searchsorted(code, [jlo, jlo + side])
            out = _piece(multiply, ri[lo:hi] - ilo, kx[lo:hi], kc[clo:chi], code[clo:chi] - jlo, ihi - ilo, min(side, len(met) - jlo), side)
            i, j = np.nonzero(out)
            yield name[i + ilo], met[j + jlo], out[i, j]

    def block(ilo: int, ihi: int):
        lo, hi = start[ilo], start[ihi]
        inner, k = distinct(kx[lo:hi], slot_of_inner)
        ones = int(degree[inner].sum())
        values = len(inner) * min(ones, width)
        if values <= most:
            yield from packed(ilo, ihi, ri[lo:hi] - ilo, k, inner)
        elif ones * THIN >= values:
            yield from square(ilo, ihi, np.sort(inner))
        elif ihi - ilo > 1:
            half = (ilo + ihi) // 2
            yield from block(ilo, half)
            yield from block(half, ihi)
        else:
            yield from alone(ilo, inner)

    def alone(ilo: int, inner: np.ndarray):
        """A row of many inner values that meet few columns each: some at a time, counts of equal columns added."""
        before = np.concatenate([[0], np.cumsum(degree[inner])])
        lo, parts = 0, []
        while lo < len(inner):
            size = len(inner) - lo
            while size > 1 and size * (before[lo + size] - before[lo]) > most:
                size = (size + 1) // 2
            parts += packed(ilo, ilo + 1, np.zeros(size, np.int64), np.arange(size), inner[lo : lo + size])
            lo += size
        met, code = np.unique(np.concatenate([j for _, j, _ in parts]), return_inverse=True)
        number = np.bincount(code, np.concatenate([x for _, _, x in parts])).astype(np.int64)
        yield np.full(len(met), name[ilo]), met, number

    ilo, size, left = 0, 0, 0
    while ilo < n:
        if not left:
            sizes = {min(side, 1 << b) for b in range(side.bit_length())} if not size else {max(1, size // 2), size, min(side, 2 * size)}
            size, left = min(sorted(sizes), key=lambda x: price(ilo, x)), SAME
        yield from block(ilo, min(ilo + size, n))
        ilo, left = ilo + size, left - 1


def _dense_at(multiply, ri: np.ndarray, kx: np.ndarray, ky: np.ndarray, cj: np.ndarray, mi: np.ndarray, mj: np.ndarray, side: int) -> int:
    """The sum of counts at the pairs (mi, mj), a piece of at most `side` rows and columns at a time.

    A piece holds rows that have pairs, ordered by their least inner value, and the columns of those pairs.
    """
    some = np.isin(ri, mi) & np.isin(kx, ky)
    ri, kx = ri[some], kx[some]
    if not len(ri):
        return 0
    names, ri = np.unique(ri, return_inverse=True)
    least = np.full(len(names), np.iinfo(np.int64).max)
    np.minimum.at(least, ri, kx)
    place = np.empty(len(names), np.int64)
    place[np.argsort(least, kind="stable")] = np.arange(len(names))
    order = np.argsort(place[ri], kind="stable")
    ri, kx = place[ri][order], kx[order]
    some = np.isin(mi, names)
    mi, mj = place[np.searchsorted(names, mi[some])], mj[some]
    order = np.argsort(mi, kind="stable")
    mi, mj = mi[order], mj[order]
    by = np.argsort(ky, kind="stable")
    ky, cj = ky[by], cj[by]
    out = 0
    for ilo in range(0, len(names), side):
        lo, hi = np.searchsorted(ri, [ilo, ilo + side])
        mlo, mhi = np.searchsorted(mi, [ilo, ilo + side])
        inner = np.unique(kx[lo:hi])
        begin = np.searchsorted(ky, inner)
        length = np.searchsorted(ky, inner, "right") - begin
        found = np.repeat(begin - (np.cumsum(length) - length), length) + np.arange(length.sum())
        met = np.intersect1d(cj[found], mj[mlo:mhi])
        kc, code = ky[found], np.searchsorted(met, cj[found])
        kept = np.isin(cj[found], met)
        kc, code = kc[kept], code[kept]
        asked = np.isin(mj[mlo:mhi], met)
        pi, pj = mi[mlo:mhi][asked] - ilo, np.searchsorted(met, mj[mlo:mhi][asked])
        for jlo in range(0, len(met), side):
            here, at = (code >= jlo) & (code < jlo + side), (pj >= jlo) & (pj < jlo + side)
            rows, cols = min(side, len(names) - ilo), min(side, len(met) - jlo)
            counts = _piece(multiply, ri[lo:hi] - ilo, kx[lo:hi], kc[here], code[here] - jlo, rows, cols, side)
            out += int(counts[pi[at], pj[at] - jlo].sum())
    return out


def _piece(multiply, r: np.ndarray, k1: np.ndarray, k2: np.ndarray, c: np.ndarray, rows: int, cols: int, side: int) -> np.ndarray:
    """Counts of a piece of the product, from pieces of the inner dimension."""
    out = np.zeros((rows, cols), np.int64)
    shared = np.intersect1d(k1, k2)
    for lo in range(0, len(shared), side):
        part = shared[lo : lo + side]
        a, b = np.searchsorted(part, k1), np.searchsorted(part, k2)
        in_a = (a < len(part)) & (part[np.minimum(a, len(part) - 1)] == k1)
        in_b = (b < len(part)) & (part[np.minimum(b, len(part) - 1)] == k2)
        m1, m2 = np.zeros((rows, len(part)), np.int8), np.zeros((len(part), cols), np.int8)
        m1[r[in_a], a[in_a]] = 1
        m2[b[in_b], c[in_b]] = 1
        out += multiply(m1, m2).astype(np.int64, copy=False)
    return out


def _distinct(df: DataFrame, dims: dict[str, list[str]], group: list[str]) -> dict[str, int]:
    """About how many values each dimension has, in the group that has most; a dimension without columns has one."""
    about = [(F.approx_count_distinct(F.xxhash64(*cols)) if cols else F.lit(1).cast("long")).alias(d) for d, cols in dims.items()]
    if group:
        found = df.groupBy(*group).agg(*about).agg(*(F.max(d).alias(d) for d in dims)).first()
    else:
        found = df.agg(*about).first()
    return {d: n or 0 for d, n in found.asDict().items()}


def _codes(tables: list[pa.Table], cols: list[str]) -> tuple[list[np.ndarray], np.ndarray]:
    """A number for each row of each table, equal for equal values of the columns, and a row (of the tables end to end) of each number."""
    total = sum(t.num_rows for t in tables)
    code = np.zeros(total, np.int64)
    for c in cols:
        values = pa.chunked_array([chunk for t in tables for chunk in t[c].chunks], tables[0][c].type).combine_chunks()
        if pa.types.is_nested(values.type):  # a fused dimension
            flat = [f.dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False) for f in values.flatten()]
        else:
            flat = [values.dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False)]
        for f in flat:
            code = np.unique(code * (int(f.max(initial=0)) + 1) + f, return_inverse=True)[1]
    _, place = np.unique(code, return_index=True)
    cuts = np.cumsum([t.num_rows for t in tables])[:-1]
    return np.split(code, cuts), place


def mm_bits(r: DataFrame, s: DataFrame, inner: str, left: str, right: str, block: int = 2048) -> DataFrame:
    """The Boolean product in Catalyst alone, for dense matrices: inner values become bits of words, rows meet columns where words share one.

    Inner values are ranked within hash groups of a few thousand; a row has a word for each 62 of them that it touches, so a pair is
    compared once a word instead of once a value. Rows are dealt to blocks of about `block` values within a word, and columns go to
    each block, so a word is as many tasks as its rows ask for.
    """
    from pyspark.sql import Window

    sizes = {**_distinct(r, {"i": [left]}, []), **_distinct(s, {"k": [inner]}, [])}
    groups = max(1, sizes["k"] // 4096)
    blocks = max(1, -(-sizes["i"] // block))
    ids = r.select(inner).distinct().join(s.select(inner).distinct(), inner).withColumn("__g", F.pmod(F.xxhash64(inner), F.lit(groups)).cast("int"))
    ids = ids.withColumn("__r", F.row_number().over(Window.partitionBy("__g").orderBy(inner)) - 1)
    ids = ids.select(inner, "__g", F.expr("cast(__r div 62 as int)").alias("__word"), F.expr("shiftleft(1L, cast(__r % 62 as int))").alias("__bit"))
    words = lambda df, side: df.join(ids, inner).groupBy(side, "__g", "__word").agg(F.bit_or("__bit").alias(f"__of_{side}"))
    a = words(r, left).withColumn("__b", F.pmod(F.xxhash64(left, F.lit(5)), F.lit(blocks)).cast("int"))
    b = words(s, right).withColumn("__b", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    met = a.join(b, ["__g", "__word", "__b"]).where(F.col(f"__of_{left}").bitwiseAND(F.col(f"__of_{right}")) != 0)
    return met.select(left, right).distinct()


#: Words of a block of right values (a power of two), and pairs of values that a band of left values meets.
WORDS, BAND_PAIRS = 4, 5_000_000


def mm_words(r: DataFrame, s: DataFrame, inner: str, left: str, right: str) -> DataFrame:
    """The Boolean product in Catalyst alone, for matrices of many pairs: a left value with the words of each block of integral right values that it meets.

    Left values are dealt to bands of neighbours. An inner value's right values go only to bands that hold it, where they become bits and
    are joined by or, so no pair is shuffled and a task's memory follows BAND_PAIRS; it is never a row after that either (`word_count`, `word_sum`).
    """
    count = lambda df, name: df.groupBy(inner).agg(F.count("*").alias(name))
    pairs = count(r, "__a").join(count(s, "__c"), inner).agg(F.sum(F.col("__a") * F.col("__c"))).first()[0] or 0
    bands = min(MOST_TASKS, max(1, -(-pairs // BAND_PAIRS)))
    held = r.select(left).distinct().repartitionByRange(bands, left)
    held = cut(held.withColumn("__t", F.spark_partition_id()), "bands")
    few = r.join(held, left).groupBy(inner, "__t").agg(F.collect_set(left).alias("__l"))
    many = s.groupBy(inner).agg(F.collect_set(right).alias("__r"))
    met = few.join(many, inner).select("__t", "__l", "__r").repartition(bands, "__t")
    rows = met.select("__t", F.explode("__l").alias(left), "__r").select("__t", left, F.explode("__r").alias("__v"))
    word, bit = F.expr("shiftright(__v, 6)"), F.expr("shiftleft(1L, cast(__v & 63 as int))")
    block = F.shiftright("__v", 6 + WORDS.bit_length() - 1)
    words = [F.bit_or(F.when(F.pmod(word, F.lit(WORDS)) == k, bit).otherwise(F.lit(0).cast("long"))).alias(f"__w{k}") for k in range(WORDS)]
    return rows.withColumn("__block", block).groupBy("__t", left, "__block").agg(*words).drop("__t")


def word_count():
    """Right values of a row of mm_words()."""
    return sum((F.bit_count(f"__w{k}").cast("long") for k in range(1, WORDS)), F.bit_count("__w0").cast("long"))


def word_sum():
    """Their sum: the first value of each word for each bit, and the places of the bits by their binary digits."""
    digits = [sum(1 << b for b in range(64) if b >> j & 1) for j in range(6)]
    signed = [m - (1 << 64) if m >> 63 else m for m in digits]
    out = F.col("__block") * (64 * WORDS) * word_count()
    for k in range(WORDS):
        w = F.col(f"__w{k}")
        if k:
            out = out + F.bit_count(w) * F.lit(64 * k).cast("long")
        for j, m in enumerate(signed):
            out = out + F.bit_count(w.bitwiseAND(F.lit(m).cast("long"))) * F.lit(1 << j).cast("long")
    return out
