"""Best-fit packing by linear grouping.

Documents are encoded in one pass to pieces (identifier, number, start, length, checksum of ids) that are written once; texts never
move. The packing problem only depends on how many pieces have each length, at most `capacity` numbers, so it is solved on the
driver whatever the corpus holds: large lengths are put into groups of equal cardinality and rounded up to their group's largest,
patterns over these few sizes come from a linear programme solved by column generation, actual lengths take the places of the
rounded ones, using the space that rounding leaves, and all others go best-fit into what is left. The plan is a table of runs (`the pieces of length L with ranks a..b
go to sequences s..`), whose size depends on the capacity alone. Ranks within a length are made without one task per length: by
(length, chunk), with the chunks' counts summed before them.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from eqdict.llm.common import staged, workdir
from eqdict.llm.tokenizing import encoder

CAPACITY = 2048
#: (groups, least share of the capacity that counts as large, room left to small pieces); see packing_plan.
SETTINGS = ((64, 0.35, 0), (64, 0.25, 32), (16, 0.25, 0), (128, 0.35, 32), (256, 0.35, 0))
#: A plan within this share of the least possible number of sequences ends the search.
NEAR_ENOUGH = 2e-4
END_ID = 0
CHUNK_ROWS = 200_000
LEAST_CHUNKS = 64
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def pieces_of(ids: np.ndarray, capacity: int) -> Iterator[tuple[int, int, int, int]]:
    """(piece, start, length, crc32): whole, or a first piece with the remainder and then full ones."""
    n, at, k = len(ids), 0, 0
    step = n if n <= capacity else n % capacity or capacity
    while at < n:
        yield k, at, step, zlib.crc32(ids[at : at + step])
        at, k, step = at + step, k + 1, capacity


def tokenized(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, end = encoder(tokenizer), np.array([END_ID], "<u4")
        for b in batches:
            out: list[tuple] = []
            for d, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids = np.concatenate([enc.array(t.as_py() or ""), end])
                out += [(d, *p) for p in pieces_of(ids, capacity)]
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            cols = list(zip(*out, strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("_text")).mapInArrow(encode, PIECES)


# --- the plan, on the counts of lengths -----------------------------------------------------------------------------------------


class _Plan:
    """Bins as classes of equal free space; every step moves whole runs, so the work does not depend on the number of pieces."""

    def __init__(self, counts: dict[int, int], capacity: int):
        self.left = dict(counts)
        self.used = dict.fromkeys(counts, 0)
        self.capacity, self.bins = capacity, 0
        self.free: dict[int, list[tuple[int, int]]] = {}  # free space -> ranges (first bin, number)
        self.runs: list[tuple[int, int, int, int, int]] = []  # length, first rank, number, first bin, offset

    def put(self, length: int, first: int, number: int, space: int) -> None:
        """The next `number` pieces of a length go to the bins from `first` on, which have `space` free."""
        self.runs.append((length, self.used[length], number, first, self.capacity - space))
        self.used[length] += number
        self.left[length] -= number

    def best_fit(self, length: int) -> None:
        """All pieces of a length: to the fullest bins that take them, then to new ones."""
        while self.left[length]:
            space = min((s for s, v in self.free.items() if s >= length and v), default=None)
            if space is None:
                each = self.capacity // length
                self.open(-(-self.left[length] // each))
                continue
            first, number = self.free[space].pop()
            take = min(number, self.left[length])
            self.put(length, first, take, space)
            self.release(first, take, space - length)
            if take < number:
                self.release(first + take, number - take, space)

    def open(self, number: int, free: bool = True) -> int:
        first, self.bins = self.bins, self.bins + number
        if free:
            self.release(first, number, self.capacity)
        return first

    def release(self, first: int, number: int, space: int) -> None:
        if number:
            self.free.setdefault(space, []).append((first, number))


def linear_groups(counts: dict[int, int], large: int, groups: int) -> list[tuple[int, int]]:
    """(rounded length, number) of at most `groups` groups, as equal in number as whole lengths allow, largest first."""
    lengths = sorted((x for x, n in counts.items() if x >= large and n), reverse=True)
    total, out, each = sum(counts[x] for x in lengths), [], 0
    for x in lengths:
        if each == 0:
            out.append([x, 0])
        out[-1][1] += counts[x]
        each += counts[x]
        if each * groups >= total:
            each = 0
    return [(x, n) for x, n in out]


def best_pattern(worth: np.ndarray, sizes: np.ndarray, capacity: int) -> np.ndarray:
    """How often each size stands in the pattern that is worth most, of all that fit."""
    most = int(capacity // sizes.min())
    levels, choice = [np.zeros(capacity + 1)], []
    for _ in range(most):  # one more piece each time, for every room at once
        room = np.arange(capacity + 1)[None, :] - sizes[:, None]
        value = np.where(room >= 0, worth[:, None] + levels[-1][np.maximum(room, 0)], -1.0)
        i = value.argmax(axis=0)
        take = value[i, np.arange(capacity + 1)]
        better = take > levels[-1] + 1e-12
        choice.append(np.where(better, i, -1))
        levels.append(np.where(better, take, levels[-1]))
    out, at, m = np.zeros(len(sizes)), capacity, most
    while m:
        i = choice[m - 1][at]
        m -= 1
        if i >= 0:
            out[i] += 1
            at -= sizes[i]
    return out


def configurations(stock: list[tuple[int, int]], capacity: int, rounds: int = 4000) -> list[tuple[np.ndarray, int]]:
    """(pattern, times) that together hold at most the stock (size, number): the linear programme of fewest patterns that hold all,
    solved by column generation and rounded down.

    Columns enter by the dual worth of the sizes; the work depends on the number of sizes and the capacity alone.
    """
    if not stock:
        return []
    sizes, need = (np.array(c, np.int64) for c in zip(*stock, strict=True))
    basis = np.diag((capacity // sizes).astype(float))
    x = need / np.diag(basis)
    for _ in range(rounds):
        worth = np.linalg.solve(basis.T, np.ones(len(sizes)))
        pattern = best_pattern(np.maximum(worth, 0.0), sizes, capacity)
        pattern[worth <= 0] = 0
        if worth @ pattern <= 1 + 1e-7:
            break
        direction = np.linalg.solve(basis, pattern)
        able = direction > 1e-9
        ratio = np.where(able, x / np.where(able, direction, 1), np.inf)
        out = int(ratio.argmin())
        x = np.maximum(x - ratio[out] * direction, 0)
        x[out] = ratio[out]
        basis[:, out] = pattern
    return [(basis[:, i].astype(np.int64), int(x[i] + 1e-6)) for i in range(len(sizes)) if x[i] >= 1 - 1e-6]


def packing_plan(counts: dict[int, int], capacity: int = CAPACITY, settings: tuple = SETTINGS) -> tuple[list[tuple[int, int, int, int, int]], int]:
    """(runs, sequences): each run is (length, first rank, number, first sequence, offset). Of the settings, all linear groupings
    of (groups, least share of the capacity that counts as large, room left to small pieces), the one with the fewest sequences."""
    best = None
    for s in settings:
        plan = _plan(counts, capacity, *s)
        if best is None or plan[1] < best[1]:
            best = plan
        if best[1] <= -(-sum(x * n for x, n in counts.items()) // capacity) * (1 + NEAR_ENOUGH):
            break
    return best


def _plan(counts: dict[int, int], capacity: int, groups: int, large: float, room: int) -> tuple[list[tuple[int, int, int, int, int]], int]:
    plan, least = _Plan(counts, capacity), max(1, int(capacity * large))
    rounded = linear_groups(counts, least, groups)
    # a size that only fits without the room is a pattern of its own
    alone = [(x, n) for x, n in rounded if x > capacity - room]
    stock = [(x, n) for x, n in rounded if x <= capacity - room]
    members: dict[int, list[int]] = {x: [] for x, _ in rounded}
    bounds = [x for x, _ in rounded]
    for y in sorted((y for y in counts if counts[y] and y >= least), reverse=True):
        members[min(x for x in bounds if x >= y)].append(y)
    chosen = [({x: 1}, n) for x, n in alone]
    chosen += [({stock[i][0]: int(m) for i, m in enumerate(p) if m}, n) for p, n in configurations(stock, capacity - room)]
    lengths = sorted((x for x in counts if x >= least), reverse=True)
    for pattern, times in sorted(chosen, key=lambda c: -max(c[0])):
        # rounded sizes become actual pieces of their groups, largest first, run by run; the last of a pattern becomes the largest
        # piece of any group that fits, as its neighbours take less room than their groups' sizes
        spaces = [(plan.open(times, False), times, capacity)]
        slots = [x for x in sorted(pattern, reverse=True) for _ in range(pattern[x])]
        for k, x in enumerate(slots):
            after = []
            for first, number, space in spaces:
                while number:
                    y = next((y for y in (lengths if k == len(slots) - 1 else members[x]) if plan.left[y] and y <= space), None)
                    if y is None:
                        after.append((first, number, space))
                        break
                    take = min(number, plan.left[y])
                    plan.put(y, first, take, space)
                    after.append((first, take, space - y))
                    first, number = first + take, number - take
            spaces = after
        for s in spaces:
            plan.release(*s)
    # what rounding down left over, and the small ones, into the room that there really is
    for x in sorted(counts, reverse=True):
        plan.best_fit(x)
    return plan.runs, plan.bins


# --- pieces to places -----------------------------------------------------------------------------------------------------------


def packed(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, settings: tuple = SETTINGS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """For every piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Null texts are empty and give the end id alone. Repeated rows are documents of their own. Null identifiers stay null. Other
    columns are ignored, whatever their names. An empty table gives no rows.
    """
    spark = docs.sparkSession
    # a number of its own for every row, fixed once written, deals equal rows and those without identifiers to all chunks
    items = staged(tokenized(docs, tokenizer, capacity, id_col, text_col).withColumn("_row", F.monotonically_increasing_id()), f"{workdir(spark, 'packing')}/pieces")
    counts = {r["length"]: r["n"] for r in items.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `capacity` rows
    runs, _ = packing_plan(counts, capacity, settings)
    runs_df = spark.createDataFrame(pa.Table.from_arrays([pa.array(c, pa.int64()) for c in (zip(*runs, strict=True) if runs else [()] * 5)], ["_len", "_rank", "_n", "_seq", "offset"]))

    chunks = max(LEAST_CHUNKS, -(-sum(counts.values()) // CHUNK_ROWS))
    local = items.withColumn("_chunk", F.pmod(F.xxhash64("_row"), F.lit(chunks)))
    before = local.groupBy("length", "_chunk").agg(F.count("*").alias("_c"))
    before = before.select("length", "_chunk", (F.sum("_c").over(Window.partitionBy("length").orderBy("_chunk")) - F.col("_c")).alias("_before"))
    rank = F.row_number().over(Window.partitionBy("length", "_chunk").orderBy("_row")) - 1
    ranked = local.withColumn("_at", rank).join(before, ["length", "_chunk"]).withColumn("_at", F.col("_at") + F.col("_before"))
    # the plan's size is bounded by the capacity, not by the corpus
    here = (F.col("length") == F.col("_len")) & (F.col("_at") >= F.col("_rank")) & (F.col("_at") < F.col("_rank") + F.col("_n"))
    out = ranked.join(F.broadcast(runs_df), here)
    return out.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("_seq") + F.col("_at") - F.col("_rank")).alias("sequence_id"), "offset")
