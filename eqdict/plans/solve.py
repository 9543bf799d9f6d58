"""Solvers of equation systems: many small binary ones at once, wide binary ones, ones over GF(2^k), and sparse ones."""

from __future__ import annotations

from functools import lru_cache

import numpy as np

from eqdict.functions.gf import field

ONE = np.uint64(1)


def eliminate_cells(rows: np.ndarray, values: np.ndarray, live: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(solved, b): Gauss-Jordan on many binary systems at once.

    rows and values are [cell, equation] (uint64, the value's bits are its right sides), live says which entries are equations, m
    is each cell's number of variables, at most 64. b is [cell, variable]; variables without a pivot are 0.
    """
    rows, values = np.where(live, rows, 0).astype(np.uint64), np.where(live, values, 0).astype(np.uint64)
    cells, width = rows.shape
    b = np.zeros((cells, 64), np.uint64)
    pivot_of = np.full((cells, 64), -1, np.int64)
    free = live.copy()
    at = np.arange(cells)
    for c in range(int(m.max()) if cells else 0):
        bit = (rows >> np.uint64(c)) & ONE
        able = (bit != 0) & free
        has = able.any(axis=1)
        p = able.argmax(axis=1)
        prow, pval = rows[at, p], values[at, p]
        bit[at, p] = 0
        hit = np.where(has[:, None], bit, 0).astype(bool)
        rows ^= np.where(hit, prow[:, None], np.uint64(0))
        values ^= np.where(hit, pval[:, None], np.uint64(0))
        free[at[has], p[has]] = False
        pivot_of[at[has], c] = p[has]
    solved = ~free.any(axis=1)
    got = pivot_of >= 0
    b[got] = values[np.nonzero(got)[0], pivot_of[got]]
    return solved, b


def eliminate_many(rows: np.ndarray, values: np.ndarray, live: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(solved, b) as eliminate_cells, for systems of any width: rows are [cell, equation, word], b is [cell, variable]."""
    rows, values = np.where(live[:, :, None], rows, 0).astype(np.uint64), np.where(live, values, 0).astype(np.uint64)
    cells, top = len(rows), int(m.max(initial=0))
    b, pivot_of, free, at = np.zeros((cells, top), np.uint64), np.full((cells, top), -1, np.int64), live.copy(), np.arange(cells)
    for c in range(top):
        bit = ((rows[:, :, c // 64] >> np.uint64(c % 64)) & ONE).astype(bool)
        able = bit & free
        has = able.any(axis=1)
        p = able.argmax(axis=1)
        bit[at, p] = False
        cell, row = np.nonzero(bit & has[:, None])
        rows[cell, row] ^= rows[cell, p[cell]]
        values[cell, row] ^= values[cell, p[cell]]
        free[at[has], p[has]] = False
        pivot_of[at[has], c] = p[has]
    got = pivot_of >= 0
    b[got] = values[np.nonzero(got)[0], pivot_of[got]]
    return ~free.any(axis=1), b


def planes_of(b: np.ndarray, k: int) -> np.ndarray:
    """[cell, k] words whose bit i is bit j of variable i."""
    place = np.arange(b.shape[1], dtype=np.uint64)
    return np.stack([np.bitwise_or.reduce(((b >> np.uint64(j)) & ONE) << place, axis=1) for j in range(k)], axis=1) if len(b) else np.zeros((0, k), np.uint64)


def by_variable(b: np.ndarray, k: int) -> np.ndarray:
    """[cell, k] words that hold the k bits of variable after variable, without gaps."""
    bits = ((b[:, :, None] >> np.arange(k, dtype=np.uint64)) & ONE).astype(np.uint8).reshape(len(b), b.shape[1] * k)
    return np.packbits(bits, axis=1, bitorder="little").view("<u8").reshape(len(b), k)


def eliminate_wide(rows: np.ndarray, values: np.ndarray, m: int) -> np.ndarray | None:
    """b of one binary system with rows [equation, word]; None if its equations are dependent.

    Eight columns at a time: their pivots' sums are listed, and each row below takes the sum that it needs in one step. Values are one
    more word of a row. Variables are then found from the last pivot to the first.
    """
    n = len(rows)
    a = np.concatenate([rows.astype(np.uint64), values.astype(np.uint64)[:, None]], axis=1)
    rank, pivots, step = 0, [], max(1, (1 << 17) // a.shape[1])
    for c in range(0, m, 8):
        if rank == n:
            break
        word = c // 64
        byte = ((a[rank:, word] >> np.uint64(c % 64)) & np.uint64(255)).astype(np.uint8)
        sums, found = np.zeros(n - rank, np.uint8), 0  # of which pivots of this block a row takes the sum
        for j in range(min(8, m - c)):
            able = (byte[found:] >> j) & 1
            p = found + int(able.argmax()) if len(able) else found
            if p >= len(byte) or not (byte[p] >> j) & 1:
                continue
            for i in range(found):
                if (sums[p] >> i) & 1:
                    a[rank + p, word:] ^= a[rank + i, word:]
            if p != found:
                for x in (a[rank:], byte, sums):
                    x[[found, p]] = x[[p, found]]
            sums[found] = 0
            hit = np.flatnonzero((byte[found + 1 :] >> j) & 1) + found + 1
            byte[hit] ^= byte[found]
            sums[hit] ^= np.uint8(1 << found)
            pivots.append(c + j)
            found += 1
        if not found:
            continue
        listed = np.zeros((1 << found, a.shape[1] - word), np.uint64)
        for i in range(found):
            listed[1 << i : 2 << i] = listed[: 1 << i] ^ a[rank + i, word:]
        for at in range(rank + found, n, step):
            a[at : at + step, word:] ^= listed[sums[at - rank : at - rank + step]]
        rank += found
    if rank < n:
        return None
    b, v = np.zeros(m, np.uint64), a[:, -1]
    for p in range(n - 1, -1, -1):
        c = pivots[p]
        b[c] = v[p]
        if b[c]:
            v[:p] ^= np.where((a[:p, c // 64] >> np.uint64(c % 64)) & ONE, b[c], np.uint64(0))
    return b


def eliminate_field(rows: np.ndarray, values: np.ndarray, k: int) -> np.ndarray | None:
    """b of one system over GF(2^k), rows [equation, variable]; None if its equations are dependent.

    Up to 8 bits all multiples of a pivot's row are listed, and the rows below take theirs from the list.
    """
    f, v = field(k), values.astype(np.int64)
    a = rows.astype(np.uint8 if k <= 8 else np.int64)
    n, m = a.shape
    rank, pivots, step = 0, [], max(1, (1 << 19) // max(1, m))
    for c in range(m):
        if rank == n:
            break
        p = rank + int((a[rank:, c] != 0).argmax())
        if not a[p, c]:
            continue
        if p != rank:
            a[[rank, p]], v[[rank, p]] = a[[p, rank]], v[[p, rank]]
        scale = f.inv(a[rank, c])
        a[rank, c:], v[rank] = f.mul(a[rank, c:], scale), f.mul(v[rank], scale)
        factor = a[rank + 1 :, c].copy()
        v[rank + 1 :] ^= f.mul(factor, v[rank])
        if k <= 8:
            listed = f.table[:, a[rank, c:]]
            for at in range(0, len(factor), step):
                a[rank + 1 + at : rank + 1 + at + step, c:] ^= listed[factor[at : at + step]]
        else:
            hit = np.flatnonzero(factor)
            a[rank + 1 + hit, c:] ^= f.mul(factor[hit, None], a[rank, None, c:])
        pivots.append(c)
        rank += 1
    if rank < n:
        return None
    b = np.zeros(m, np.int64)
    for p in range(n - 1, -1, -1):
        b[pivots[p]] = v[p]
        v[:p] ^= f.mul(a[:p, pivots[p]], v[p])
    return b


def independent_field(rows: np.ndarray, k: int) -> np.ndarray:
    """Which of many systems [system, equation, variable] over GF(2^k) have independent equations; all are eliminated together."""
    f, a = field(k), rows.astype(np.int64)
    systems, n, m = a.shape
    free, at = np.ones((systems, n), bool), np.arange(systems)
    for c in range(m):
        able = (a[:, :, c] != 0) & free
        has = able.any(axis=1)
        p = able.argmax(axis=1)
        free[at[has], p[has]] = False
        pivot = a[at, p, c:]
        scaled = f.mul(pivot, f.inv(np.where(has, pivot[:, 0], 1))[:, None])
        a[:, :, c:] ^= f.mul(np.where(free & has[:, None], a[:, :, c], 0)[:, :, None], scaled[:, None, :])
    return ~free.any(axis=1)


# --- lists of all small matrices ------------------------------------------------------------------------------------------------


@lru_cache(maxsize=4)
def inverses(r: int) -> np.ndarray:
    """For each r x r binary matrix (row i in bits i*r..) the number of its inverse, or -1. r is at most 4: 65,536 matrices."""
    if not 1 <= r <= 4:
        raise ValueError("matrices of up to 16 bits can be listed")
    ids = np.arange(1 << (r * r), dtype=np.uint64)
    rows = np.stack([(ids >> np.uint64(i * r)) & np.uint64((1 << r) - 1) for i in range(r)], axis=1)
    solved, b = eliminate_cells(rows, np.broadcast_to(ONE << np.arange(r, dtype=np.uint64), rows.shape), np.ones(rows.shape, bool), np.full(len(ids), r))
    out = np.zeros(len(ids), np.int64)
    for i in range(r):
        out |= (b[:, i] << np.uint64(i * r)).astype(np.int64)
    out[~solved] = -1
    return out


def solve_listed(rows: np.ndarray, values: np.ndarray, r: int) -> tuple[np.ndarray, np.ndarray]:
    """(solved, b) of r x r systems by looking their matrices up; rows and values are [cell, r]."""
    ids = np.bitwise_or.reduce(rows << (np.arange(r, dtype=np.uint64) * np.uint64(r)), axis=1).astype(np.int64)
    inv = inverses(r)[ids]
    return inv >= 0, times(np.where(inv < 0, 0, inv).astype(np.uint64), values, r)


@lru_cache(maxsize=4)
def field_inverses(r: int, k: int) -> np.ndarray:
    """For each r x r matrix over GF(2^k), its k-bit entries row by row in its number, the entries of its inverse; -1 if there is none.

    k r^2 is at most 16, so r is 1 or 2 but for k = 1.
    """
    if k * r * r > 16 or (r > 2 and k > 1):
        raise ValueError("matrices of up to 16 bits can be listed")
    if k == 1:
        inv = inverses(r)
        bits = (inv[:, None] >> np.arange(r * r)) & 1
        return np.where(inv[:, None] < 0, -1, bits)
    f = field(k)
    ids = np.arange(1 << (k * r * r), dtype=np.int64)
    e = (ids[:, None] >> (k * np.arange(r * r))) & ((1 << k) - 1)
    det = e[:, 0] if r == 1 else f.mul(e[:, 0], e[:, 3]) ^ f.mul(e[:, 1], e[:, 2])
    scale = np.array([0, *(f.inv(d) for d in range(1, 1 << k))], np.int64)[det]
    turned = np.ones_like(e) if r == 1 else e[:, [3, 1, 2, 0]]  # signs do not matter here
    return np.where((det == 0)[:, None], -1, f.mul(turned, scale[:, None]))


def solve_listed_field(rows: np.ndarray, values: np.ndarray, r: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(solved, b) of systems rows [cell, r, r] over GF(2^k) by looking their matrices up; values are [cell, r]."""
    f = field(k)
    inv = field_inverses(r, k)[(rows.reshape(len(rows), r * r) << (k * np.arange(r * r))).sum(axis=1)].reshape(rows.shape)
    ok = inv[:, 0, 0] >= 0
    b = np.bitwise_xor.reduce(f.mul(np.where(inv < 0, 0, inv), values[:, None, :]), axis=2)
    return ok, b


def times(matrix: np.ndarray, values: np.ndarray, r: int) -> np.ndarray:
    """Listed matrices times vectors of k-bit values."""
    b = np.zeros((len(values), r), np.uint64)
    for i in range(r):
        for j in range(r):
            b[:, i] ^= np.where((matrix >> np.uint64(i * r + j)) & ONE, values[:, j], np.uint64(0))
    return b


def answer_table(r: int) -> list[int]:
    """Parity of row & plane for each row and plane of r bits, at row * 2^r + plane."""
    if r > 5:
        raise ValueError("an answer table holds 4^r entries; r is at most 5")
    return [(row & plane).bit_count() & 1 for row in range(1 << r) for plane in range(1 << r)]


# --- shared inverses ------------------------------------------------------------------------------------------------------------


class InverseCache:
    """The seed and inverse of the equation set that belongs to a set of positions: the smallest seed that gives full rank.

    Rows depend on position and seed only, so cells with one position set share the set of equations whatever their values. The
    oldest sets are forgotten beyond `most`; they can be made again.
    """

    def __init__(self, row_of, max_seed: int = 200, most: int = 200_000):
        self.row_of, self.max_seed, self.most = row_of, max_seed, most  # row_of(seed, positions, m) -> uint64 rows
        self.known: dict[bytes, tuple[int, np.ndarray]] = {}
        self.hits = 0

    def __call__(self, positions: np.ndarray) -> tuple[int, np.ndarray]:
        """(seed, inverse): row i of the inverse has a bit for each value that b_i sums. Positions are sorted."""
        seeds, inverse = self.many(positions[None, :])
        return int(seeds[0]), inverse[0]

    def many(self, sets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(seed of each, inverses [set, row]) of distinct sets [set, position]; those not known are solved together."""
        m = sets.shape[1]
        names = [s.tobytes() for s in np.ascontiguousarray(sets, np.int64)]
        new = np.array([n not in self.known for n in names], bool)
        self.hits += int((~new).sum())
        todo = np.flatnonzero(new)
        unit = ONE << np.arange(m, dtype=np.uint64)
        found: dict[int, tuple[int, np.ndarray]] = {}
        for seed in range(self.max_seed):
            if not len(todo):
                break
            rows = self.row_of(seed, sets[todo].ravel(), m).reshape(len(todo), m)
            solved, b = eliminate_cells(rows, np.broadcast_to(unit, rows.shape), np.ones(rows.shape, bool), np.full(len(todo), m))
            for i in np.flatnonzero(solved).tolist():
                found[int(todo[i])] = seed, b[i, :m]
            todo = todo[~solved]
        if len(todo):
            raise RuntimeError("no seed gives full rank")
        got = [found[i] if i in found else self.known[n] for i, n in enumerate(names)]
        self.known.update((names[i], x) for i, x in found.items())
        while len(self.known) > self.most:
            del self.known[next(iter(self.known))]
        return np.array([s for s, _ in got], np.int64), np.array([b for _, b in got], np.uint64).reshape(len(names), m)


def multiply_each(inverse: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Each cell's inverse [cell, row] times its values [cell, m]."""
    out = np.zeros_like(values)
    for i in range(values.shape[1]):
        for j in range(values.shape[1]):
            out[:, i] ^= np.where((inverse[:, i] >> np.uint64(j)) & ONE, values[:, j], np.uint64(0))
    return out


def multiply_batch(inverse: np.ndarray, values: np.ndarray) -> np.ndarray:
    """One inverse times many value vectors [cell, m], all together."""
    out = np.zeros_like(values)
    for i, bits in enumerate(inverse):
        use = np.flatnonzero((bits >> np.arange(values.shape[1], dtype=np.uint64)) & ONE)
        if len(use):
            out[:, i] = np.bitwise_xor.reduce(values[:, use], axis=1)
    return out


# --- sparse systems -------------------------------------------------------------------------------------------------------------


def dense_words(places: np.ndarray, m: int) -> np.ndarray:
    """Rows [equation, word] of a binary sparse system; a place drawn twice cancels."""
    rows = np.zeros((len(places), max(1, -(-m // 64))), np.uint64)
    for j in range(places.shape[1]):
        rows[np.arange(len(places)), places[:, j] // 64] ^= ONE << (places[:, j] % 64).astype(np.uint64)
    return rows


def solve_structured(places: np.ndarray, values: np.ndarray, m: int) -> np.ndarray | None:
    """b of a sparse binary system: variables in one equation only are set aside first, what is left is eliminated densely."""
    n, t = places.shape
    count = np.bincount(places.ravel(), minlength=m)
    by_var: list[list[int]] = [[] for _ in range(m)]
    for i, row in enumerate(places.tolist()):
        for p in row:
            by_var[p].append(i)
    gone, order = np.zeros(n, bool), []
    stack = [v for v in range(m) if count[v] == 1]
    while stack:
        v = stack.pop()
        if count[v] != 1:
            continue
        e = next(i for i in by_var[v] if not gone[i])
        gone[e] = True
        order.append((e, v))
        for p in places[e].tolist():
            count[p] -= 1
            if count[p] == 1:
                stack.append(p)
    b = np.zeros(m, np.uint64)
    core = np.flatnonzero(~gone)
    if len(core):
        used = np.unique(places[core])
        small = eliminate_wide(dense_words(np.searchsorted(used, places[core]), len(used)), values[core], len(used))
        if small is None:
            return None
        b[used] = small
    for e, v in reversed(order):
        rest = np.bitwise_xor.reduce(b[[p for p in places[e].tolist() if p != v]], initial=0)
        b[v] = np.uint64(values[e]) ^ rest
    return b


def _berlekamp_massey(s: np.ndarray, f) -> np.ndarray:
    """The shortest recurrence c (c[0] = 1) of a sequence over a field: sum of c[i] s[j - i] is 0."""
    c, b = np.zeros(len(s) + 1, np.int64), np.zeros(len(s) + 1, np.int64)
    c[0] = b[0] = 1
    size, shift, last = 0, 1, 1
    for i in range(len(s)):
        d = int(s[i]) ^ int(f.dot(c[1 : size + 1], s[i - size : i][::-1])) if size else int(s[i])
        if d == 0:
            shift += 1
            continue
        before = c.copy()
        c[shift:] ^= f.mul(f.mul(d, f.inv(last)), b[: len(b) - shift])
        if 2 * size <= i:
            size, b, last, shift = i + 1 - size, before, d, 1
        else:
            shift += 1
    return c[: size + 1]


def minimal_rows(series: np.ndarray, f) -> tuple[np.ndarray, np.ndarray]:
    """(degrees, rows [row, power, column]) of polynomials v whose product with the power series [power, b, b] is a polynomial of
    smaller degree up to the series' length: a basis of all, built one power at a time.

    At each power the rows' residues are eliminated, those of small degree first; rows that served as pivots are multiplied by z.
    """
    length, b, _ = series.shape
    basis, degree = np.zeros((2 * b, length + 2, 2 * b), np.uint8), np.repeat([0, 1], b)
    basis[np.arange(2 * b), 0, np.arange(2 * b)] = 1
    whole = np.zeros((length, 2 * b, b), np.uint8)
    whole[:, :b] = series
    whole[0, b:] = np.eye(b, dtype=np.uint8)
    back = np.ascontiguousarray(whole[::-1].transpose(2, 0, 1))
    top = 1
    for k in range(length):
        span = min(top, k + 1)
        left, right = basis[:, :span].reshape(2 * b, 1, -1), back[:, length - 1 - k : length - 1 - k + span].reshape(1, b, -1)  # powers i of the basis with k - i of the series
        rest = np.bitwise_xor.reduce(f.table.take((left.astype(np.uint16) << 8) | right), axis=2).astype(np.int64)
        order, pivots = np.argsort(degree, kind="stable").tolist(), []
        for c in range(b):
            p = next((r for r in order if r not in pivots and rest[r, c]), None)
            if p is None:
                continue
            pivots.append(p)
            others = np.array([r for r in order[order.index(p) + 1 :] if r not in pivots and rest[r, c]], np.int64)
            if len(others):
                factor = f.mul(rest[others, c], f.inv(rest[p, c]))
                rest[others] ^= f.mul(factor[:, None], rest[p][None])
                basis[others, :top] ^= f.table.take((factor.astype(np.uint16) << 8)[:, None, None] | basis[p, None, :top])
        if pivots:
            basis[pivots, 1 : top + 1] = basis[pivots, :top]
            basis[pivots, 0] = 0
            degree[pivots] += 1
            top = min(top + 1, length + 1)
    return degree, basis[:, :, :b]


def solve_block(places: np.ndarray, values: np.ndarray, m: int, seed: int = 0, width: int = 8, tries: int = 3) -> np.ndarray | None:
    """b of a square sparse binary system by its action on blocks of `width` vectors, in GF(2^8).

    With a block, the matrix is applied 2 n / width times to make the sequence and n / width times for the answer, where single
    vectors need 3 n. As in solve_krylov the result is checked, and values are done 8 bits at a time.
    """
    n, _ = places.shape
    if n != m:
        raise ValueError("a square system is needed")
    f, out = field(8), np.zeros(m, np.uint64)
    width = max(1, min(width, n))
    columns = np.ascontiguousarray(places.T)

    def product(x):
        """The matrix times a block, whose rows are words where they hold 8 bytes; or times one vector."""
        words = np.ascontiguousarray(x).view(np.uint64) if x.ndim == 2 and x.shape[1] == 8 else x
        out = words[columns[0]]
        for c in columns[1:]:
            out ^= words[c]
        return out.view(np.uint8).reshape(x.shape)

    r = np.random.Generator(np.random.PCG64(seed))
    for low in range(0, 32, 8):
        d = ((values.astype(np.uint64) >> np.uint64(low)) & np.uint64(255)).astype(np.uint8)
        if not d.any():
            continue
        for _ in range(tries):
            probe, free = r.integers(0, 256, (n, width)), r.integers(0, 256, (n, width), dtype=np.uint8)
            probes = (probe.T << 8).astype(np.uint16)[:, None]
            start = product(free)
            start[:, 0] = d
            length = 2 * -(-n // width) + 4
            series, x = np.zeros((length, width, width), np.int64), start
            for i in range(length):
                # transposed, so that rows stand for what multiplies from the right
                series[i] = np.bitwise_xor.reduce(f.table.take(probes | np.ascontiguousarray(x.T)), axis=2).T
                x = product(x)
            degree, rows = minimal_rows(series, f)
            for p in np.argsort(degree, kind="stable")[:width]:
                top = int(degree[p])
                lead = rows[p, top].astype(np.int64)
                if top < 1 or top >= rows.shape[1] or not lead[0]:
                    continue
                part = lambda c: np.bitwise_xor.reduce(f.table[start, c[None, :]], axis=1)
                b = part(rows[p, 0])
                for j in range(1, top):
                    b = product(b) ^ part(rows[p, j])
                b = b ^ f.dot(free[:, 1:].astype(np.int64), lead[None, 1:]).astype(np.uint8)
                b = f.mul(b.astype(np.int64), f.inv(lead[0])).astype(np.uint8)
                if (product(b) == d).all():
                    out |= b.astype(np.uint64) << np.uint64(low)
                    break
            else:
                # polynomials of all n degrees are the matrix's own: where their lowest terms are dependent, so is the matrix
                least = np.argsort(degree, kind="stable")[:width]
                lowest = np.stack([rows[p, degree[p]] if degree[p] < rows.shape[1] else np.zeros(width, np.uint8) for p in least])
                if degree[least].sum() == n and eliminate_field(lowest, np.zeros(width, np.int64), 8) is None:
                    return None
                continue
            break
        else:
            return None
    return out


def solve_krylov(places: np.ndarray, values: np.ndarray, m: int, seed: int = 0, tries: int = 3) -> np.ndarray | None:
    """b of a square sparse binary system by its minimal polynomial on the right side, in GF(2^8).

    The matrix is only ever multiplied with vectors. Its entries are 0 and 1, so each bit of the values is a right side of its own
    and 8 of them fit one vector over GF(2^8); wider values are done 8 bits at a time. The result is checked; None if every try
    fails, as for a singular matrix.
    """
    n, _ = places.shape
    if n != m:
        raise ValueError("a square system is needed")
    f, out = field(8), np.zeros(m, np.uint64)
    columns = np.ascontiguousarray(places.T)

    def matvec(x):
        out = x[columns[0]]
        for c in columns[1:]:
            out ^= x[c]
        return out

    r = np.random.Generator(np.random.PCG64(seed))
    for low in range(0, 32, 8):
        d = ((values.astype(np.uint64) >> np.uint64(low)) & np.uint64(255)).astype(np.int64)
        if not d.any():
            continue
        for _ in range(tries):
            u, x, s = r.integers(0, 256, n), d, []
            for _ in range(2 * n):
                s.append(int(f.dot(u, x)))
                x = matvec(x)
            c = _berlekamp_massey(np.array(s), f)
            if len(c) < 2 or c[-1] == 0:
                continue
            # with q(A) d = 0 for the reversed recurrence q, b is -(q - q_0)(A)/A d / q_0
            b, x = np.zeros(n, np.int64), d
            for i in range(1, len(c)):
                b ^= f.mul(c[len(c) - 1 - i], x)
                x = matvec(x)
            b = f.mul(b, f.inv(c[-1]))
            if (matvec(b) == d).all():
                out |= b.astype(np.uint64) << np.uint64(low)
                break
        else:
            return None
    return out


