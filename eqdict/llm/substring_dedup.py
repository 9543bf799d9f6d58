"""Removal of word windows that repeat anywhere, by level-wise doubling.

Windows of a short length are compared first; only those that repeat are extended to twice that length, until the wanted length is
reached or no candidate survives. A window can only repeat if the two shorter ones that make it up do.

Texts are written once, in blocks of bounded size, to a folder that all executors share; afterwards only hashes move. For a level,
each block sends its candidates' distinct hashes, sorted and packed, to as many parts as the corpus needs for a bounded number of
hashes in each; a part finds those that occur twice and answers each block with a bit for each hash it sent. A very frequent
window is one hash from each block. Shorter levels only filter, so they send 32 bits beside the part; the last level, which decides,
sends 96 bits.
"""

from __future__ import annotations

import hashlib
import itertools
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eqdict.llm.common import drop, parts_of, staged, window_hashes, word_hashes, workdir

WINDOW = 35
START = 9
BLOCK_BYTES = 6 << 20
PART_HASHES = 4_000_000
#: Fewer hashes are not worth a part of their own.
LEAST_HASHES = 250_000
SENT = "part long, block string, keys binary, more binary, twice binary"
ANSWER = "block string, part long, bits binary"
RESULT = "doc_id long, n_words long, n_removed long, kept_sha256 string"


def levels(window: int, start: int) -> list[int]:
    """Lengths from start on, each at most twice the last one, up to the window."""
    out = [min(start, window)]
    while out[-1] < window:
        out.append(min(2 * out[-1], window))
    return out


def uri(folder: str) -> str:
    return folder if "://" in folder or folder.startswith("file:") else f"file://{folder}"


def written_blocks(docs: DataFrame, folder: str, id_col: str, text_col: str, block_bytes: int) -> DataFrame:
    """(block, n_words) of blocks of documents below folder; a block counts once its row is committed."""
    where = f"{uri(folder)}/blocks"

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, path = pafs.FileSystem.from_uri(where)
        fs.create_dir(path, recursive=True)
        ids, texts, size = [], [], 0

        def flush() -> pa.RecordBatch:
            name = uuid.uuid4().hex
            table = pa.table({"doc_id": pa.array(ids, pa.int64()), "text": pa.array(texts, pa.large_binary())})
            with fs.open_output_stream(f"{path}/{name}.arrow") as out, pa.ipc.new_file(out, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
                w.write_table(table)
            return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([sum(map(_count, texts))], pa.int64())], ["block", "n_words"])

        for b in batches:
            for d, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                ids.append(d)
                texts.append((t.as_py() or "").encode("utf-8", "surrogatepass"))
                size += len(texts[-1]) + 64
                if size >= block_bytes:
                    yield flush()
                    ids, texts, size = [], [], 0
        if ids:
            yield flush()

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("_text"))
    return staged(rows.mapInArrow(write, "block string, n_words long"), f"{folder}/index")


def _count(data: bytes) -> int:
    return len(data.split())


class Block:
    """A block's texts and the hashes of their windows, laid end to end."""

    def __init__(self, folder: str, name: str):
        fs, path = pafs.FileSystem.from_uri(f"{uri(folder)}/blocks/{name}.arrow")
        with fs.open_input_file(path) as f:
            table = pa.ipc.open_file(f).read_all()
        self.ids, self.texts = table.column("doc_id").to_pylist(), table.column("text").to_pylist()
        words = [word_hashes(t) for t in self.texts]
        self.sizes = np.array([len(w) for w in words], np.int64)
        self.ends = np.cumsum(self.sizes)
        self.words = np.concatenate([np.zeros(0, np.uint64), *words])
        self.left = np.repeat(self.ends, self.sizes) - np.arange(len(self.words))  # words from a place to its text's end

    def other_words(self) -> np.ndarray:
        """The words' hashes by another, independent function."""
        return np.concatenate([np.zeros(0, np.uint64), *(word_hashes(t, 1) for t in self.texts)])

    def candidates(self, length: int, before: int, repeated: np.ndarray | None) -> np.ndarray:
        """Places where a window of this length may repeat: all, or those whose first and last shorter windows do."""
        ok = self.left >= length
        if repeated is not None:
            step = length - before
            n = max(len(ok) - step, 0)  # later places have fewer words left than the window needs
            ok[:n] &= repeated[:n] & repeated[step:]
        return np.flatnonzero(ok)

    def coded(self, at: np.ndarray, length: int, parts: int, last: bool) -> tuple[np.ndarray, np.ndarray | None]:
        """Codes whose order is that of their parts; for the last level with a second hash."""
        if not len(at):
            return np.zeros(0, np.uint64), np.zeros(0, np.uint32) if last else None
        h = window_hashes(self.words, length)[at]
        if last:
            return h, (window_hashes(self.other_words(), length)[at] >> np.uint64(32)).astype(np.uint32)
        return part_of(h, parts).astype(np.uint64) << np.uint64(32) | h & np.uint64(0xFFFFFFFF), None


def part_of(h: np.ndarray, parts: int) -> np.ndarray:
    return ((h >> np.uint64(32)) * np.uint64(parts) >> np.uint64(32)).astype(np.int64)


def distinct(code: np.ndarray, more: np.ndarray | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order, starts of the groups in it, group of each entry)."""
    order = np.argsort(code)
    c = code[order]
    new = np.ones(len(c), bool)
    new[1:] = c[1:] != c[:-1]
    if more is not None:
        m = more[order]
        if (~new[1:] & (m[1:] != m[:-1])).any():  # equal codes of different windows: hardly ever
            order = np.lexsort((more, code))
            c, m = code[order], more[order]
            new[1:] = (c[1:] != c[:-1]) | (m[1:] != m[:-1])
    group = np.empty(len(c), np.int64)
    group[order] = np.cumsum(new) - 1
    return order, np.flatnonzero(new), group


def packets(block: Block, name: str, at: np.ndarray, length: int, parts: int, last: bool) -> list[tuple]:
    """Rows of SENT: the block's candidates (in a part below 0, which hands them through), then hashes for each part."""
    mask = np.zeros(len(block.words), bool)
    mask[at] = True
    out = [(-1 - hash_name(name) % parts, name, np.packbits(mask).tobytes(), None, None)]
    code, more = block.coded(at, length, parts, last)
    order, starts, _ = distinct(code, more)
    if len(starts):
        twice = np.diff(np.append(starts, len(order))) > 1
        c = code[order[starts]]
        part = part_of(c, parts) if last else (c >> np.uint64(32)).astype(np.int64)
        cuts = np.flatnonzero(np.diff(part, prepend=-1, append=parts))
        for lo, hi in itertools.pairwise(cuts.tolist()):
            keys = c[lo:hi] if last else c[lo:hi].astype("<u4")
            out.append((int(part[lo]), name, keys.tobytes(), more[order[starts[lo:hi]]].tobytes() if last else None, np.packbits(twice[lo:hi]).tobytes()))
    return out


def hash_name(name: str) -> int:
    return int(name[:8], 16)


def answered(block: Block, rows: list[tuple], length: int, parts: int, last: bool) -> np.ndarray:
    """Which places' windows of this length repeat, from a block's rows of ANSWER."""
    by = {p: b for p, b in rows}
    out = np.zeros(len(block.words), bool)
    state = next(b for p, b in by.items() if p < 0)
    at = np.flatnonzero(np.unpackbits(np.frombuffer(state, np.uint8), count=len(out)))
    code, more = block.coded(at, length, parts, last)
    order, starts, group = distinct(code, more)
    if len(starts):
        c = code[order[starts]]
        part = part_of(c, parts) if last else (c >> np.uint64(32)).astype(np.int64)
        cuts = np.flatnonzero(np.diff(part, prepend=-1, append=parts))
        bits = np.concatenate([np.unpackbits(np.frombuffer(by[int(part[lo])], np.uint8), count=hi - lo) for lo, hi in itertools.pairwise(cuts.tolist())])
        out[at] = bits[group].astype(bool)
    return out


def found_repeated(last: bool):
    """Kernel of a task that has one part: hashes that two blocks sent, or one block met twice. Rows below 0 are handed through."""

    def answer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: dict[int, list[tuple]] = {}
        for b in batches:
            for part, *row in zip(*(b.column(c).to_pylist() for c in ("part", "block", "keys", "more", "twice")), strict=True):
                rows.setdefault(part, []).append(row)
        for part, own in rows.items():
            names, keys, more, twice = zip(*own, strict=True)
            bits = list(keys)
            if part >= 0:
                arrays = [np.frombuffer(k, "<u8" if last else "<u4") for k in keys]
                code, cuts = np.concatenate(arrays), np.cumsum([0, *map(len, arrays)]).tolist()
                extra = np.concatenate([np.frombuffer(m, "<u4") for m in more]) if last else None
                many = np.concatenate([np.unpackbits(np.frombuffer(t, np.uint8), count=len(a)) for t, a in zip(twice, arrays, strict=True)]).astype(bool)
                order, starts, group = distinct(code, extra)
                hit = np.diff(np.append(starts, len(order))) > 1
                hit |= np.logical_or.reduceat(many[order], starts)
                flags = hit[group]
                bits = [np.packbits(flags[a:b]).tobytes() for a, b in itertools.pairwise(cuts)]
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array([part] * len(names), pa.int64()), pa.array(bits, pa.binary())], ["block", "part", "bits"])

    return answer


def _sent(rows: list[tuple]) -> pa.Table:
    kinds = (pa.int64(), pa.string(), pa.binary(), pa.binary(), pa.binary())
    cols = list(zip(*rows, strict=True)) or [()] * 5
    return pa.table([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["part", "block", "keys", "more", "twice"])


def without_repeats(docs: DataFrame, window: int = WINDOW, start: int = START, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False, block_bytes: int = BLOCK_BYTES, part_hashes: int = PART_HASHES) -> DataFrame:
    """For every row: doc_id, n_words, n_removed, kept_sha256 and, with_text, kept_text.

    A word goes if a window of so many words that covers it also starts anywhere else, in the same text or another, all judged on
    the input. Kept words are joined by one space. Null and empty texts have no words; texts shorter than the window keep all.
    Repeated rows are texts of their own, so a long text that is there twice goes entirely. Null identifiers stay null. Other
    columns are ignored, whatever their names. An empty table gives no rows.
    """
    spark = docs.sparkSession
    folder = workdir(spark, "substring")
    index = written_blocks(docs, folder, id_col, text_col, block_bytes)
    total, n_blocks = index.agg(F.coalesce(F.sum("n_words"), F.lit(0)), F.count("*")).first()
    parts = max(-(-total // part_hashes), min(parts_of(spark), -(-total // LEAST_HASHES)), 1)
    # rows are few and small but stand for whole blocks of text, so their number of tasks is not left to adaptive coalescing
    block_tasks = max(-(-n_blocks // 4), min(parts_of(spark), n_blocks), 1)
    by_part = lambda df: df.repartitionById(parts, F.pmod("part", F.lit(parts)).cast("int"))  # noqa: E731  each part has a task of its own
    by_block = lambda df: df.repartition(block_tasks, "block")
    lengths = levels(window, start)

    def opening(length: int, last: bool):
        def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for name in b.column("block").to_pylist():
                    block = Block(folder, name)
                    yield from _sent(packets(block, name, block.candidates(length, 0, None), length, parts, last)).to_batches()

        return send

    def extending(before: int, length: int, last: bool):
        def send(table: pa.Table) -> pa.Table:
            name = table.column("block")[0].as_py()
            block = Block(folder, name)
            seen = answered(block, list(zip(table.column("part").to_pylist(), table.column("bits").to_pylist(), strict=True)), before, parts, False)
            return _sent(packets(block, name, block.candidates(length, before, seen), length, parts, last))

        return send

    def closing(table: pa.Table) -> pa.Table:
        block = Block(folder, table.column("block")[0].as_py())
        seen = answered(block, list(zip(table.column("part").to_pylist(), table.column("bits").to_pylist(), strict=True)), window, parts, True)
        edge = np.zeros(len(block.words) + 1, np.int64)
        edge[:-1] += seen
        edge[np.flatnonzero(seen) + window] -= 1
        gone = np.cumsum(edge[:-1]) > 0
        removed, hashes, kept = [], [], []
        for text, n, end in zip(block.texts, block.sizes.tolist(), block.ends.tolist(), strict=True):
            mine = gone[end - n : end]
            words = text.split()
            left = b" ".join(itertools.compress(words, (~mine).tolist()) if mine.any() else words)
            removed.append(int(mine.sum()))
            hashes.append(hashlib.sha256(left).hexdigest())
            kept.append(left.decode("utf-8", "surrogatepass") if with_text else None)
        out = {"doc_id": pa.array(block.ids, pa.int64()), "n_words": pa.array(block.sizes), "n_removed": pa.array(removed, pa.int64()), "kept_sha256": pa.array(hashes, pa.string())}
        return pa.table(out | ({"kept_text": pa.array(kept, pa.string())} if with_text else {}))

    sent = by_block(index.select("block")).mapInArrow(opening(lengths[0], lengths[0] == window), SENT)
    for i, length in enumerate(lengths):
        replies = staged(by_part(sent).mapInArrow(found_repeated(length == window), ANSWER), f"{folder}/answers-{length}")
        if i:
            drop(spark, f"{folder}/answers-{lengths[i - 1]}")
        if length < window:
            sent = by_block(replies).groupBy("block").applyInArrow(extending(length, lengths[i + 1], lengths[i + 1] == window), SENT)
    return by_block(replies).groupBy("block").applyInArrow(closing, RESULT + (", kept_text string" if with_text else ""))
