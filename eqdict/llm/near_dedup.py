"""Near-duplicate documents by SetSketch registers, with every link confirmed on full sets of word shingles.

One pass makes each document's shingle set, its checksum and its registers; documents with equal sets stand behind the one with
the smallest identifier. Bands of registers are keys. Where a key is shared, pairs with its smallest member are estimated by the
joint likelihood of their registers, and the likely ones confirmed; these links' components cover most of what there is to find.

What is left are members of one bucket in different components. They meet in units: members of buckets with one main component, of
neighbouring size classes, as sets of sizes further apart cannot be similar enough, dealt to blocks of bounded size. In a unit the joint likelihood is taken of
each pair between components; only members of a pair that may reach the threshold send their sets, and units of these yield a
spanning forest of their links, never a group's pairs. Large sets travel in slices by hash and are compared pair by pair.

A link is missed if two documents share no band (chance under 10^-6 at the threshold by the registers' law, `band_rows`) or if their
estimate lies five deviations below it (`setsketch.surely`, about 10^-6).
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from math import log

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eqdict.llm import setsketch
from eqdict.llm.common import LOWER, components, drop, staged, window_hashes, word_hashes, workdir

#: Most rows of a side of a unit, and most shingles that they hold (but for one row that holds more).
BLOCK = 256
BLOCK_SHINGLES = 250_000
#: Most shingles of a slice; a larger set travels in several, by hash.
SLICE = 1 << 16
SKETCH_SHINGLES = 1_000_000
SKETCHED = "doc_id long, n long, set_digest binary, regs binary"
SETS = "rep long, sid long, n long, level int, slice int, items array<long>"
UNIT = ["main", "u", "i", "j"]
LIKELY = "main long, u int, i long, j long, side int, rep long, n long, comp long, partner long, partner_comp long"
#: Rows, and shingles, of units that one call of a kernel gets.
CALL_ROWS = 8_192
CALL_SHINGLES = 1_000_000
#: Pairs whose registers are compared at a time.
CALL_PAIRS = 16_384


def band_rows(percent: int) -> tuple[int, int]:
    """(rows, bands) for a threshold in percent: as many rows as keep the chance that a pair at it shares no band under 10^-6."""
    t = percent / 100
    chance = min(setsketch.equal_chance(t, u) for u in (0.5, t / (1 + t)))
    fit = [r for r in range(1, 9) if (1 - chance**r) ** (setsketch.REGISTERS // r) < 1e-6]
    if not fit:
        raise ValueError(f"{setsketch.REGISTERS} registers cannot find pairs of {percent} % in bands")
    return fit[-1], setsketch.REGISTERS // fit[-1]


def shingles(text: str | None, words: int) -> np.ndarray:
    """Hashes of the distinct shingles of a text: of so many words each, or one of all words if there are fewer; A-Z in lower case."""
    if not text:
        return np.zeros(0, np.uint64)
    w = word_hashes(text.encode("utf-8", "surrogatepass").translate(LOWER))
    if len(w) == 0:
        return w
    return np.unique(window_hashes(w, min(words, len(w))))


def digest_of(s: np.ndarray) -> bytes:
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


def sketched(docs: DataFrame, words: int, id_col: str, text_col: str) -> DataFrame:
    def sketch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, at = b.column(0), 0
            while at < b.num_rows:  # a bounded number of shingles at a time
                sets, to, size = [], at, 0
                while to < b.num_rows and size < SKETCH_SHINGLES:
                    sets.append(shingles(b.column(1)[to].as_py(), words))
                    size, to = size + len(sets[-1]), to + 1
                yield pa.RecordBatch.from_arrays(
                    [ids.slice(at, to - at), pa.array([len(s) for s in sets], pa.int64()), pa.array([digest_of(s) if len(s) else None for s in sets], pa.binary()), pa.array(setsketch.sketches(sets), pa.binary())],
                    ["doc_id", "n", "set_digest", "regs"],
                )
                at = to

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("_text")).mapInArrow(sketch, SKETCHED)


def slice_level(n: int, size: int = SLICE) -> int:
    """A set of n shingles travels in 2^level slices of about `size` at most."""
    return max(0, (n - 1) // size).bit_length()


def level_col(n: Column, size: int = SLICE) -> Column:
    return F.when(n <= size, 0).otherwise(F.length(F.bin(F.floor((n - 1) / size)))).cast("int")


def full_sets(docs: DataFrame, wanted: DataFrame, words: int, percent: int, id_col: str, text_col: str, size: int = SLICE) -> DataFrame:
    """SETS of the wanted(rep, set_digest): the sorted shingle hashes of a document that has both, in slices.

    A set is there at its own level and, where the largest set that it can be similar to has another, at that one too. A document
    that is there twice gives its rows twice.
    """

    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.list_(pa.int64()))
        done = lambda rows: pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows, strict=True)) or [()] * 6, kinds, strict=True)], [x.split()[0] for x in SETS.split(", ")])
        for b in batches:
            rows, held = [], 0
            for rep, digest, sid, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3), strict=True):
                s = shingles(text.as_py(), words)
                if digest_of(s) != digest:
                    continue
                for level in range(slice_level(len(s), size), slice_level(len(s) * 100 // percent, size) + 1):
                    cuts = np.searchsorted(s >> np.uint64(64 - level) if level else np.zeros(len(s), np.uint64), np.arange(2**level + 1))
                    for i in range(2**level):
                        rows.append((rep, sid, len(s), level, i, s[cuts[i] : cuts[i + 1]].view(np.int64)))
                        held += len(rows[-1][5]) + 8
                        if held > SKETCH_SHINGLES // 4:
                            yield done(rows)
                            rows, held = [], 0
            yield done(rows)

    texts = docs.select(F.col(id_col).cast("long").alias("rep"), F.col(text_col).alias("_text"))
    return texts.join(wanted, "rep").select("rep", "set_digest", F.xxhash64("set_digest").alias("sid"), "_text").mapInArrow(make, SETS)


def likely(pairs: DataFrame, percent: int) -> DataFrame:
    """Those of pairs(a, b, na, nb, ra, rb, ...) whose estimated similarity reaches the threshold, without ra and rb."""
    schema = pairs.drop("ra", "rb").schema

    def estimate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 20_000):
                part = b.slice(at, 20_000)
                ra, rb = (np.frombuffer(b"".join(part.column(c).to_pylist()), "<u2").reshape(part.num_rows, -1) for c in ("ra", "rb"))
                na, nb = (part.column(c).to_numpy(zero_copy_only=False).astype(float) for c in ("na", "nb"))
                keep = setsketch.joint_estimate(ra, rb, na, nb) >= percent / 100
                yield part.select(schema.names).filter(pa.array(keep))

    return pairs.mapInArrow(estimate, schema)


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int, *more: str, size: int = SLICE) -> DataFrame:
    """(a, b, more) of the pairs(a, sa, na, b, sb, nb, more) whose full sets are similar enough.

    Common shingles are counted slice by slice, so that no set need be in memory as a whole.
    """
    names = ["a", "sa", "na", "b", "sb", "nb", *more]
    p = pairs.select(*names, level_col(F.greatest("na", "nb"), size).alias("level"))
    p = p.withColumn("slice", F.explode(F.sequence(F.lit(0), F.call_function("shiftleft", F.lit(1), F.col("level")) - 1)))
    of = lambda x: sets.select(F.col("rep").alias(x), F.col("sid").alias(f"s{x}"), "level", "slice", F.col("items").alias(f"i{x}"))
    both = p.join(of("a"), ["a", "sa", "level", "slice"]).join(of("b"), ["b", "sb", "level", "slice"])
    part = both.select(*names, "slice", F.size(F.array_intersect("ia", "ib")).cast("long").alias("c"))
    # the maximum takes one of a document's equal rows
    common = part.groupBy(*names, "slice").agg(F.max("c").alias("c")).groupBy(*names).agg(F.sum("c").alias("c"))
    return common.where(f"100 * c >= {percent} * (na + nb - c)").select("a", "b", *more).distinct()


# --- members of one bucket in different components --------------------------------------------------------------------------------


def units_of(table: pa.Table) -> Iterator[tuple[int, int]]:
    """First row and end of each unit of a table that is sorted by unit."""
    cols = [table.column(c).to_numpy() for c in UNIT]
    new = np.zeros(table.num_rows, bool)
    new[:1] = True
    for c in cols:
        new[1:] |= c[1:] != c[:-1]
    cuts = np.append(np.flatnonzero(new), table.num_rows).tolist()
    return zip(cuts[:-1], cuts[1:], strict=True)


def by_unit(table: pa.Table) -> pa.Table:
    return table.sort_by([(c, "ascending") for c in (*UNIT, "side")])


def maybe_linked(percent: int, small: int):
    """Kernel over some units: the rows that have a partner on the other side and in another component whose estimate does not rule
    a link out. In classes from `small` on, whose sets travel in slices, the pairs themselves."""
    cut = setsketch.surely(percent / 100)

    def judge(table: pa.Table) -> pa.Table:
        table = by_unit(table)
        side, comp, n, u = (table.column(c).to_numpy() for c in ("side", "comp", "n", "u"))
        regs = np.frombuffer(b"".join(table.column("regs").to_pylist()), "<u2").reshape(len(side), -1)
        kept, partner = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]

        def flush(parts: list[tuple[np.ndarray, np.ndarray]]) -> None:
            x, y = (np.concatenate(v) for v in zip(*parts, strict=True))
            fits = (comp[x] != comp[y]) & (100 * np.minimum(n[x], n[y]) >= percent * np.maximum(n[x], n[y]))
            x, y = x[fits], y[fits]
            for at in range(0, len(x), CALL_PAIRS):
                a, b = x[at : at + CALL_PAIRS], y[at : at + CALL_PAIRS]
                more, less = (regs[a] > regs[b]).sum(axis=1), (regs[a] < regs[b]).sum(axis=1)
                near = setsketch.fitted(more, less, n[a].astype(float), n[b].astype(float), steps=20) >= cut
                kept.append(a[near])
                partner.append(b[near])

        parts, held = [], 0
        for lo, hi in units_of(table):
            mid = lo + int(np.searchsorted(side[lo:hi], 1))
            left, right = np.arange(lo, mid), np.arange(mid, hi)
            parts.append((np.repeat(left, len(right)), np.tile(right, len(left))))
            held += len(parts[-1][0])
            if held > 8 * CALL_PAIRS:
                flush(parts)
                parts, held = [], 0
        if parts:
            flush(parts)
        x, y = np.concatenate(kept), np.concatenate(partner)
        pairwise = u[x] >= small
        alone = np.unique(np.concatenate([x[~pairwise], y[~pairwise]]))
        own, other = np.concatenate([alone, x[pairwise]]), y[pairwise]
        none = pa.nulls(len(alone), pa.int64())
        out = {c: table.column(c).take(pa.array(own)) for c in (*UNIT, "side", "rep", "n", "comp")}
        with_none = lambda c: pa.chunked_array([none, table.column(c).take(pa.array(other)).combine_chunks()])
        return pa.table(out | {"partner": with_none("rep"), "partner_comp": with_none("comp")})

    return judge


def block_links(percent: int):
    """Kernel over some units: rows of side 0 against rows of side 1 of each, links between components as a spanning forest of these."""

    def links(table: pa.Table) -> pa.Table:
        table = by_unit(table)
        found = [link(table.slice(lo, hi - lo)) for lo, hi in units_of(table)]
        return pa.table({"a": pa.array([x for f in found for x, _ in f], pa.int64()), "b": pa.array([x for f in found for _, x in f], pa.int64())})

    def link(table: pa.Table) -> list[tuple[int, int]]:
        side, comp, n = (table.column(c).to_numpy() for c in ("side", "comp", "n"))
        items = table.column("items").combine_chunks()
        offsets, values = items.offsets.to_numpy(), items.values.to_numpy()
        owner = np.repeat(np.arange(len(side), dtype=np.int32), np.diff(offsets))
        values = values[offsets[0] : offsets[-1]]
        left, right = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        row = np.zeros(len(side), np.int64)
        row[left], row[right] = np.arange(len(left)), np.arange(len(right))
        # only what occurs on both sides counts
        order = np.argsort(values, kind="stable")
        values, owner = values[order], owner[order]
        code = np.cumsum(np.concatenate([[0], values[1:] != values[:-1]])) if len(values) else np.zeros(0, np.int64)
        on_left = np.zeros(code[-1] + 1 if len(code) else 0, bool)
        on_right = on_left.copy()
        on_left[code[side[owner] == 0]] = True
        on_right[code[side[owner] == 1]] = True
        both = on_left & on_right
        new = np.cumsum(both) - 1
        keep = both[code]
        code, owner = new[code[keep]], owner[keep]
        common = np.zeros((len(left), len(right)), np.float32)
        n_common = int(both.sum())
        wide = max(1, min(n_common, 2_000_000 // max(len(left), len(right), 1)))
        for lo in range(0, n_common, wide):
            here = slice(*np.searchsorted(code, (lo, lo + wide)))
            x, y = np.zeros((len(left), wide), np.float32), np.zeros((len(right), wide), np.float32)
            o, c = owner[here], code[here] - lo
            is_left = side[o] == 0
            x[row[o[is_left]], c[is_left]] = 1
            y[row[o[~is_left]], c[~is_left]] = 1
            common += x @ y.T
        common = common.astype(np.int64)
        union = n[left][:, None] + n[right][None, :] - common
        hit = (100 * common >= percent * union) & (comp[left][:, None] != comp[right][None, :])
        root: dict[int, int] = {}

        def find(v: int) -> int:
            while root.get(v, v) != v:
                root[v] = root.get(root[v], root[v])
                v = root[v]
            return v

        out = []
        for i, j in zip(*np.nonzero(hit), strict=True):
            a, b = find(int(comp[left[i]])), find(int(comp[right[j]]))
            if a != b:
                root[a] = b
                out.append((int(comp[left[i]]), int(comp[right[j]])))
        return out

    return links


def unit_rows(open_: DataFrame, percent: int, work: str, block: int = BLOCK, size: int = SLICE) -> tuple[DataFrame, int, int]:
    """(rows of units: UNIT, side, rep, sid, comp, n; how many; the first class whose sets may travel in slices) of open_(main, rep,
    sid, comp, n).

    A unit has members of class u that are not in the main component on side 0, and members of classes u - 1 to u + 1 on side 1.
    Sizes of a class lie within a factor of 100 / percent, so rows bound shingles. Numbers of blocks are written, so that joins with
    those of a hot component have an exchange on both sides, which adaptive execution splits.
    """
    width = max(1.001 * log(100 / percent), 0.02)
    small = int(log(size) / width) - 1
    class_ = F.floor(F.log(F.col("n").cast("double")) / width).cast("int")
    rows = open_.withColumn("c", class_)
    few = rows.where("comp <> main").select("main", F.col("c").alias("u"), F.lit(0).alias("side"), "rep", "sid", "comp", "n")
    every = rows.select("main", F.explode(F.array(F.col("c") - 1, F.col("c"), F.col("c") + 1)).alias("u"), F.lit(1).alias("side"), "rep", "sid", "comp", "n")
    both = few.unionByName(every)
    count = both.groupBy("main", "u").agg(F.count_if(F.col("side") == 0).alias("few"), F.count_if(F.col("side") == 1).alias("all")).where("few > 0")
    per = F.when(F.col("u") >= small, block).otherwise(F.least(F.lit(block), F.greatest(F.lit(1), F.floor(BLOCK_SHINGLES / F.exp((F.col("u") + 2) * width)))))
    blocks = lambda c: F.ceil(F.col(c) / per).cast("long")
    shape = staged(count.select("main", "u", blocks("few").alias("few"), blocks("all").alias("all"), (F.col("few") * blocks("all") + F.col("all") * blocks("few")).alias("rows")), f"{work}/shapes")
    total = shape.agg(F.coalesce(F.sum("rows"), F.lit(0))).first()[0]
    dealt = both.join(shape.drop("rows"), ["main", "u"]).withColumn("_h", F.xxhash64("rep", "sid"))
    first = F.col("side") == 0
    own, other = F.pmod("_h", F.when(first, F.col("few")).otherwise(F.col("all"))), F.when(first, F.col("all")).otherwise(F.col("few"))
    spread = dealt.withColumn("_own", own).withColumn("_other", F.explode(F.sequence(F.lit(0).cast("long"), other - 1)))
    i, j = F.when(first, F.col("_own")).otherwise(F.col("_other")), F.when(first, F.col("_other")).otherwise(F.col("_own"))
    return spread.select("main", "u", i.alias("i"), j.alias("j"), "side", "rep", "sid", "comp", "n"), total, small


def in_calls(units: DataFrame, calls: int):
    """Whole units, dealt to so many calls of a kernel."""
    return units.groupBy(F.pmod(F.xxhash64(*UNIT), F.lit(max(1, calls))).alias("_call"))


def rest_links(buckets: DataFrame, comps: DataFrame, reps: DataFrame, sets: DataFrame, percent: int, work: str, block: int = BLOCK, size: int = SLICE) -> DataFrame:
    """Links (a, b) between components comps(rep, comp) whose members share a bucket. Of a bucket with several components the most
    frequent one is its main one; members of the others are compared with all that share a bucket with the same main one."""
    m = buckets.join(comps, "rep", "left").withColumn("comp", F.coalesce("comp", "rep"))
    by = m.groupBy("key", "comp").agg(F.count("*").alias("c"))
    main = by.groupBy("key").agg(F.max(F.struct("c", -F.col("comp"))).alias("top"), F.count("*").alias("k")).where("k > 1").select("key", (-F.col("top.col2")).alias("main"))
    units, total, small = unit_rows(m.join(main, "key").select("main", "rep", "sid", "comp", "n").distinct(), percent, work, block, size)
    known = units.join(reps.select("rep", "sid", "regs"), ["rep", "sid"]).select(*UNIT, "side", "rep", "comp", "n", "regs")
    maybe = staged(in_calls(known, -(-total // CALL_ROWS)).applyInArrow(maybe_linked(percent, small), LIKELY), f"{work}/maybe")
    rows = maybe.where("partner is null")
    held = rows.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    rows = rows.drop("n").join(sets.where("level = 0"), "rep").select(*UNIT, "side", "comp", "n", "items")
    links = in_calls(rows, -(-held // CALL_SHINGLES)).applyInArrow(block_links(percent), "a long, b long")
    side = lambda x: reps.select(F.col("rep").alias(x), F.col("sid").alias(f"s{x}"), F.col("n").alias(f"n{x}"))
    large = maybe.where("partner is not null").select(F.col("rep").alias("a"), F.col("partner").alias("b"), F.col("comp").alias("ca"), F.col("partner_comp").alias("cb")).distinct()
    large = confirmed(large.join(side("a"), "a").join(side("b"), "b"), sets, percent, "ca", "cb", size=size)
    return staged(links.unionByName(large.select(F.col("ca").alias("a"), F.col("cb").alias("b"))), f"{work}/links-rest")


def near_groups(docs: DataFrame, words: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK, size: int = SLICE) -> DataFrame:
    """For every row: doc_id, n_shingles, component_id, kept.

    Documents are linked if 100 * intersection >= percent * union of their shingle sets; component_id is the smallest identifier
    that links reach, and a row is kept if that is its own. Null and empty texts, and those without words, have no shingles and no
    links. A null identifier links with nothing, has component_id null and is kept. Rows that share an identifier are one node;
    each gives a row. Other columns are ignored, whatever their names. An empty table gives no rows. block, size: most rows of a side
    of a unit and shingles of a slice.
    """
    work = workdir(docs.sparkSession, "near")
    rows_, bands = band_rows(percent)
    all_ = staged(sketched(docs, words, id_col, text_col), f"{work}/sketches")
    known = all_.where("doc_id is not null and n > 0")
    reps = known.groupBy("set_digest").agg(F.min("doc_id").alias("rep"), F.max("n").alias("n"), F.max("regs").alias("regs"))
    reps = staged(reps.select("set_digest", F.xxhash64("set_digest").alias("sid"), "rep", "n", "regs"), f"{work}/sets")

    key = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda i: F.xxhash64(i, F.substring("regs", i * (2 * rows_) + 1, F.lit(2 * rows_))))
    banded = reps.select("rep", "sid", "n", F.explode(key).alias("key"))
    shared = banded.groupBy("key").agg(F.min("rep").alias("first"), F.max("rep").alias("last")).where("first < last").select("key", "first")
    buckets = staged(banded.join(shared, "key").select("key", "first", "rep", "sid", "n"), f"{work}/buckets")

    wanted = reps.select("rep", "sid", "set_digest").join(buckets.select("rep", "sid").distinct(), ["rep", "sid"], "left_semi").select("rep", "set_digest")
    sets = staged(full_sets(docs, wanted, words, percent, id_col, text_col, size), f"{work}/full")

    stars = buckets.where("first < rep").select(F.col("rep").alias("a"), F.col("sid").alias("sa"), F.col("first").alias("b")).distinct()
    side = lambda x: reps.select(F.col("rep").alias(x), F.col("sid").alias(f"s{x}"), F.col("n").alias(f"n{x}"), F.col("regs").alias(f"r{x}"))
    near_size = f"100 * least(na, nb) >= {percent} * greatest(na, nb)"
    pairs = likely(stars.join(side("a"), ["a", "sa"]).join(side("b"), "b").where(near_size), percent)
    # rows that share an identifier but not a set are one node
    member = known.select("doc_id", "set_digest").join(reps.select("set_digest", "rep"), "set_digest")
    twice = member.groupBy("doc_id").agg(F.min("rep").alias("b"), F.max("rep").alias("_last")).where("b < _last").select("doc_id", "b")
    same = member.join(twice, "doc_id").where("rep <> b").select(F.col("rep").alias("a"), "b")
    links = confirmed(pairs, sets, percent, size=size).unionByName(same)

    comps = staged(components(links, f"{work}/first").withColumnsRenamed({"node": "rep", "root": "comp"}), f"{work}/comps")
    joined = components(rest_links(buckets, comps, reps, sets, percent, work, block, size), f"{work}/second")
    # a set's root by its first links, and that root's by those found after
    root = reps.select("set_digest", "rep").join(comps, "rep", "left").select("set_digest", F.coalesce("comp", "rep").alias("node")).join(joined, "node", "left")
    root = staged(root.select("set_digest", F.coalesce("root", "node").alias("comp")), f"{work}/roots")
    for used in ("sets", "buckets", "full", "shapes", "maybe", "links-rest", "comps", "first", "second"):
        drop(docs.sparkSession, f"{work}/{used}")

    out = all_.select("doc_id", "n", "set_digest").join(root, "set_digest", "left")
    comp = F.when(F.col("doc_id").isNotNull(), F.coalesce("comp", "doc_id"))
    out = out.select("doc_id", F.col("n").alias("n_shingles"), comp.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def near_distinct(docs: DataFrame, words: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without the rows whose component has a smaller identifier; columns and names as they are."""
    groups = near_groups(docs.select(id_col, text_col), words, percent, id_col, text_col)
    gone = groups.where(~F.col("kept")).select(F.col("doc_id").alias("_gone")).distinct()
    names = docs.columns
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in names)).alias("_row"))
    return rows.join(gone, F.col(f"_row.{id_col}").cast("long") == F.col("_gone"), "left_anti").select("_row.*")
