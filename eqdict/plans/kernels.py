"""Grouped kernels: from the digests and values of a group of buckets to solved bucket rows.

Pure functions of their rows and the seeds, so a repeated task gives the same result.
"""

from __future__ import annotations

from functools import lru_cache
from math import ceil

import numpy as np
import pyarrow as pa

from eqdict.functions import rows as R
from eqdict.functions.hashing import TableHash, xxhash64_np
from eqdict.functions.theory import slack_for
from eqdict.plans import solve as S
from eqdict.spec import DictSpec


def sorted_columns(table: pa.Table) -> tuple[np.ndarray, ...]:
    bucket, hi, lo, v = (table.column(c).to_numpy() for c in ("bucket", "key_hi", "key_lo", "value"))
    order = np.lexsort((lo, hi, bucket))
    return bucket[order], hi[order], lo[order], v[order]


def bucket_rows(bucket, n_keys, split, func, cells, side, tries, splits) -> pa.Table:
    """One row per bucket. cells: (owner, m, seed, extra, planes: a list of arrays or one [cell, k] array); side: (owner, hi, lo,
    value), both in order of owner."""
    n = len(bucket)
    offsets = lambda owner: np.searchsorted(owner, np.arange(n + 1)).astype(np.int32)
    owner, m, seed, extra, planes = cells
    if isinstance(planes, np.ndarray):
        flat, cuts = np.ascontiguousarray(planes).view(np.int64).ravel(), (np.arange(len(planes) + 1) * planes.shape[1]).astype(np.int32)
    else:
        flat = np.concatenate([np.zeros(0, np.int64), *(p.astype(np.uint64).view(np.int64) for p in planes)])
        cuts = np.cumsum([0, *(len(p) for p in planes)]).astype(np.int32)
    cell = pa.StructArray.from_arrays([pa.array(m, pa.int32()), pa.array(seed, pa.int32()), pa.array(extra, pa.int32()), pa.ListArray.from_arrays(cuts, pa.array(flat, pa.int64()))], ["m", "seed", "extra", "planes"])
    so, sh, sl, sv = side
    left = pa.StructArray.from_arrays([pa.array(sh, pa.int64()), pa.array(sl, pa.int64()), pa.array(sv, pa.int64())], ["key_hi", "key_lo", "value"])
    return pa.table(
        {
            "bucket": pa.array(bucket, pa.int64()), "n_keys": pa.array(n_keys, pa.int32()), "split_seed": pa.array(split, pa.int32()), "func_no": pa.array(func, pa.int32()),
            "cells": pa.ListArray.from_arrays(offsets(owner), cell), "side": pa.ListArray.from_arrays(offsets(so), left), "tries": pa.array(tries, pa.int64()), "splits": pa.array(splits, pa.int64()),
        }
    )


def table_hash(spec: DictSpec, n: int) -> TableHash:
    return TableHash(spec.table_len or 2 * spec.cap**2, spec.n_funcs or ceil(2 * np.log2(max(n, 2))), spec.seed)


def two_level(spec: DictSpec, n: int):
    """Kernel: splits each bucket into cells until none is over its cap, then solves all cells of the group together."""

    def kernel(table: pa.Table) -> pa.Table:
        bucket, hi, lo, v = sorted_columns(table)
        names, first, count = np.unique(bucket, return_index=True, return_counts=True)
        nb = len(names)
        of = np.repeat(np.arange(nb), count)
        good = count <= spec.cap
        split, func, splits = np.zeros(nb, np.int64), np.zeros(nb, np.int64), np.zeros(nb, np.int64)
        x, y = hi.copy(), lo.copy()
        if spec.hashing == "table":
            hash_, todo = table_hash(spec, n), good.copy()
            for f in range(hash_.n_funcs):
                if not todo.any():
                    break
                own = np.flatnonzero(todo[of])
                index = hash_.index_np(f, hi[own], lo[own])
                order = np.lexsort((index, of[own]))
                same = (np.diff(index[order]) == 0) & (np.diff(of[own][order]) == 0)
                clash = np.zeros(nb, bool)
                clash[of[own][order[1:][same]]] = True
                done = todo & ~clash
                func[done] = f
                take = done[of[own]]
                x[own[take]], y[own[take]] = index[take], f
                todo &= clash
            good &= ~todo
        n_cells = np.where(good, np.maximum(1, np.ceil(count / spec.cell_mean)), 0).astype(np.int64)
        base = np.concatenate([[0], np.cumsum(n_cells)])
        cell = np.full(len(hi), -1, np.int64)
        todo = good.copy()
        for s in range(spec.split_tries):
            own = np.flatnonzero(todo[of])
            if not len(own):
                break
            h = xxhash64_np(R.SPLIT, np.full(len(own), s, np.int64), x[own], y[own])
            cell[own] = base[of[own]] + (h >> np.uint64(1)).astype(np.int64) % n_cells[of[own]]
            size = np.bincount(cell[own], minlength=base[-1])
            over = np.zeros(nb, bool)
            over[of[own[size[cell[own]] > spec.cell_cap]]] = True
            split[todo], splits[todo] = s, s + 1
            todo &= over
        good &= ~todo
        inside = good[of]
        owner = np.repeat(np.arange(nb), n_cells)
        live_cells = good[owner]
        size = np.bincount(cell[inside], minlength=base[-1]) if base[-1] else np.zeros(0, np.int64)
        m, seed, tries = np.where(live_cells, size + np.where(size > 0, spec.c, 0), 0), np.zeros(base[-1], np.int64), np.zeros(base[-1], np.int64)
        extra = np.zeros(base[-1], np.int64)
        width = int(size.max()) if len(size) else 0
        planes = np.zeros((base[-1], spec.k), np.uint64) if spec.field == "binary" else [np.zeros(0, np.uint64)] * base[-1]
        keys = np.flatnonzero(inside)
        keys = keys[np.argsort(cell[keys], kind="stable")]
        place = np.arange(len(keys)) - np.repeat(np.concatenate([[0], np.cumsum(size)])[:-1], size) if len(keys) else keys
        todo_cells = np.flatnonzero(size > 0)
        solve = _shared(spec) if spec.method == "shared_inverse" else _full if spec.field == "full" else _binary
        failed = solve(spec, todo_cells, cell[keys], place, x[keys], y[keys], v[keys], m, seed, extra, tries, planes, width)
        bad_cell = np.zeros(base[-1] + 1, bool)
        bad_cell[failed] = True
        m[failed] = 0  # their keys are in the side dictionary
        out = ~inside | bad_cell[cell]
        side = np.flatnonzero(out)
        keep = live_cells
        kept = planes[keep] if spec.field == "binary" else [p for p, k in zip(planes, keep, strict=True) if k]
        return bucket_rows(
            names, count, split, func, (owner[keep], m[keep], seed[keep], extra[keep], kept),
            (of[side], hi[side], lo[side], v[side]), np.bincount(owner, weights=tries, minlength=nb).astype(np.int64), splits,
        )

    return kernel


def _blocked(cells: np.ndarray, at: np.ndarray, place: np.ndarray, width: int, *cols: np.ndarray):
    """Columns of the keys of some cells as [cell, place] arrays, and which entries are keys."""
    row = np.full(int(at.max(initial=-1)) + 1, -1, np.int64)
    row[cells] = np.arange(len(cells))
    own = row[at] >= 0
    live = np.zeros((len(cells), width), bool)
    live[row[at[own]], place[own]] = True
    out = []
    for c in cols:
        a = np.zeros((len(cells), width), c.dtype)
        a[row[at[own]], place[own]] = c[own]
        out.append(a)
    return live, out


def _binary(spec, todo, at, place, x, y, v, m, seed, extra, tries, planes, width) -> np.ndarray:
    for s in range(spec.seed_tries):
        if not len(todo):
            break
        live, (bx, by, bv) = _blocked(todo, at, place, width, x, y, v)
        rows = R.masks_np(s, bx.ravel(), by.ravel(), np.repeat(m[todo], width), spec.kind, spec.t, spec.window).reshape(bx.shape)
        values = bv.astype(np.uint64)
        if spec.solver == "listed":
            solved, b = np.zeros(len(todo), bool), np.zeros((len(todo), 64), np.uint64)
            for r in range(1, 5):
                same = np.flatnonzero(m[todo] == r)
                if len(same):
                    solved[same], b[same, :r] = S.solve_listed(rows[same, :r], values[same, :r], r)
        else:
            # a square system in which some variable has no equation is singular, so it need not be eliminated
            able = np.flatnonzero((np.bitwise_or.reduce(np.where(live, rows, 0), axis=1) == R.mask_np(m[todo])) | (spec.c > 0))
            solved, b = np.zeros(len(todo), bool), np.zeros((len(todo), 64), np.uint64)
            solved[able], b[able] = S.eliminate_cells(rows[able], values[able], live[able], m[todo[able]])
        tries[todo] += 1
        planes[todo[solved]] = (S.by_variable if spec.by_variable else S.planes_of)(b[solved], spec.k)
        seed[todo[solved]] = s
        todo = todo[~solved]
    return todo


def _full(spec, todo, at, place, x, y, v, m, seed, extra, tries, planes, width) -> np.ndarray:
    left = []
    if spec.solver == "listed":  # all cells of a size together
        for r in np.unique(m[todo]).tolist():
            cells = todo[m[todo] == r]
            for s in range(spec.seed_tries):
                if not len(cells):
                    break
                _, (bx, by, bv) = _blocked(cells, at, place, width, x, y, v)
                rows = R.coefs_np(s, bx[:, :r].ravel(), by[:, :r].ravel(), r, spec.k).reshape(len(cells), r, r)
                solved, b = S.solve_listed_field(rows, bv[:, :r].astype(np.int64), r, spec.k)
                tries[cells] += 1
                for i in np.flatnonzero(solved).tolist():
                    planes[cells[i]], seed[cells[i]] = b[i], s
                cells = cells[~solved]
            for c in cells:
                planes[c] = np.zeros(r, np.int64)
            left += cells.tolist()
        return np.array(left, np.int64)
    for c in todo:
        own = at == c
        for s in range(spec.seed_tries):
            tries[c] += 1
            b = S.eliminate_field(R.coefs_np(s, x[own], y[own], int(m[c]), spec.k), v[own].astype(np.int64), spec.k)
            if b is not None:
                planes[c], seed[c] = b, s
                break
        else:
            planes[c] = np.zeros(int(m[c]), np.int64)
            left.append(c)
    return np.array(left, np.int64)


def position_rows(seed, positions: np.ndarray, m) -> np.ndarray:
    return R.masks_np(seed, positions.astype(np.int64), np.zeros(len(positions), np.int64), m)


def positions_np(seed: np.ndarray, x: np.ndarray, y: np.ndarray, m: np.ndarray) -> np.ndarray:
    """A key's position among m^2."""
    return (xxhash64_np(R.POSITION, seed, x, y) >> np.uint64(1)).astype(np.int64) % (m * m)


@lru_cache(maxsize=1)
def shared_cache() -> S.InverseCache:
    """The inverses that a Python worker has made so far; workers outlive tasks, so few sets of positions serve a whole build."""
    return S.InverseCache(position_rows)


def _shared(spec):
    def solve(spec, todo, at, place, x, y, v, m, seed, extra, tries, planes, width) -> np.ndarray:
        cells, positions, values = [], [], []
        none = np.iinfo(np.int64).max
        for s in range(spec.seed_tries):
            if not len(todo):
                break
            live, (bx, by, bv) = _blocked(todo, at, place, width, x, y, v)
            p = positions_np(np.full(bx.size, s, np.int64), bx.ravel(), by.ravel(), np.repeat(np.maximum(m[todo], 1), width)).reshape(bx.shape)
            p = np.where(live, p, none)
            order = np.argsort(p, axis=1, kind="stable")
            p, bv = np.take_along_axis(p, order, 1), np.take_along_axis(bv, order, 1)
            clash = ((np.diff(p, axis=1) == 0) & (p[:, 1:] != none)).any(axis=1)
            tries[todo] += 1
            extra[todo[~clash]] = s
            cells.append(todo[~clash]), positions.append(p[~clash]), values.append(bv[~clash].astype(np.uint64))
            todo = todo[clash]
        if cells:
            own, p, bv = np.concatenate(cells), np.concatenate(positions), np.concatenate(values)
            for size in np.unique(m[own]):  # cells with one set of positions have one inverse
                here = np.flatnonzero(m[own] == size)
                sets, which = np.unique(p[here, :size], axis=0, return_inverse=True)
                seeds, inverse = shared_cache().many(sets)
                b = np.zeros((len(here), 64), np.uint64)
                b[:, :size] = S.multiply_each(inverse[which.ravel()], bv[here, :size])
                planes[own[here]], seed[own[here]] = S.planes_of(b, spec.k), seeds[which.ravel()]
        return todo

    return solve


def single(spec: DictSpec):
    """Kernel: one system for each bucket. Dense rows of any width, rows over GF(2^k), or t-sparse ones."""

    def kernel(table: pa.Table) -> pa.Table:
        bucket, hi, lo, v = sorted_columns(table)
        names, first, count = np.unique(bucket, return_index=True, return_counts=True)
        if spec.method == "one_level" and spec.field == "binary":
            return _dense_together(spec, names, first, count, hi, lo, v)
        owner, ms, seeds, extras, planes, tries = [], [], [], [], [], []
        for b, (at, n) in enumerate(zip(first, count, strict=True)):
            h, w, values = hi[at : at + n], lo[at : at + n], v[at : at + n]
            m, t = system_size(spec, int(n))
            for s in range(spec.seed_tries):
                got = one_system(spec, s, h, w, values, m, t)
                if got is not None:
                    break
            else:
                raise RuntimeError(f"{n} equations in {m} variables stayed dependent for {spec.seed_tries} seeds")
            owner.append(b), ms.append(m), seeds.append(s), extras.append(t), planes.append(got), tries.append(s + 1)
        none = np.zeros(0, np.int64)
        return bucket_rows(names, count, np.zeros(len(names)), np.zeros(len(names)), (np.array(owner), ms, seeds, extras, planes), (none, none, none, none), tries, np.zeros(len(names)))

    return kernel


def _dense_together(spec: DictSpec, names, first, count, hi, lo, v) -> pa.Table:
    """All buckets of a group, each one dense system, eliminated column by column together; a seed at a time for what is unsolved."""
    none, nb = np.zeros(0, np.int64), len(names)
    m, seeds, tries = count + spec.c, np.zeros(nb, np.int64), np.zeros(nb, np.int64)
    of = np.repeat(np.arange(nb), count)
    place = np.arange(len(of)) - np.repeat(first, count)
    planes: list[np.ndarray] = [np.zeros(0, np.uint64)] * nb
    todo, words, widest = np.arange(nb), max(1, -(-int(m.max(initial=0)) // 64)), int(count.max(initial=0))
    for s in range(spec.seed_tries):
        if not len(todo):
            break
        live, (bx, by, bv) = _blocked(todo, of, place, widest, hi, lo, v)
        x, y, own = bx.ravel(), by.ravel(), np.repeat(m[todo], widest)
        rows = np.stack([xxhash64_np(R.ROW, s, i, x, y) & R.mask_np(np.clip(own - 64 * i, 0, 64)) for i in range(words)], axis=1).reshape(len(todo), widest, words)
        solved, b = S.eliminate_many(rows, bv, live, m[todo])
        tries[todo] += 1
        for i in np.flatnonzero(solved).tolist():
            width = max(1, -(-int(m[todo[i]]) // 64))
            padded = np.zeros(width * 64, np.uint64)
            padded[: int(m[todo[i]])] = b[i, : int(m[todo[i]])]
            planes[todo[i]] = S.planes_of(padded.reshape(width, 64), spec.k).T.ravel()  # plane after plane
        seeds[todo[solved]] = s
        todo = todo[~solved]
    if len(todo):
        raise RuntimeError(f"{len(todo)} systems stayed dependent for {spec.seed_tries} seeds")
    return bucket_rows(names, count, np.zeros(nb), np.zeros(nb), (np.arange(nb), m, seeds, np.zeros(nb, np.int64), planes), (none, none, none, none), tries, np.zeros(nb))


def system_size(spec: DictSpec, n: int) -> tuple[int, int]:
    """(variables, places of a row; 0 for dense rows)."""
    if spec.method == "sparse":
        t = spec.t or 3
        m = max(t, ceil(n * (spec.slack or slack_for(t))))
        return m, t
    if spec.method == "global_sparse":
        t = spec.t or R.odd_log(n)
        return n, min(t, n) if n else 0
    return n + spec.c, 0


def one_system(spec: DictSpec, s: int, hi, lo, v, m: int, t: int) -> np.ndarray | None:
    """What is stored for a solved system: k planes of words, or a word for each variable."""
    if t:
        places = R.places_np(np.full(len(hi), s, np.int64), hi, lo, np.full(len(hi), m, np.int64), t, spec.replace)
        if spec.solver in ("krylov", "block"):
            # most square systems that fail are singular, so the next seed is a better try than the same matrix again
            return (S.solve_krylov if spec.solver == "krylov" else S.solve_block)(places, v, m, tries=1)
        if spec.replace:
            return S.eliminate_wide(S.dense_words(places, m), v, m)
        return S.solve_structured(places, v, m)
    if spec.field == "full":
        return S.eliminate_field(R.coefs_np(s, hi, lo, m, spec.k), v.astype(np.int64), spec.k)
    b = S.eliminate_wide(R.words_np(s, hi, lo, m), v, m)
    if b is None:
        return None
    width = max(1, -(-m // 64))
    padded = np.zeros(width * 64, np.uint64)
    padded[:m] = b
    return S.planes_of(padded.reshape(width, 64), spec.k).T.ravel()  # plane after plane
