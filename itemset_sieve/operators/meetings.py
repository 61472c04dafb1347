"""Pairs that meet under covering keys, found without a table of keys.

Keys of one block of the family depend on the positions of that block alone. Positions are dealt to groups of blocks;
a task has the positions of a group and the bits of all items there, makes the keys of all itemsets for a few blocks at
a time, looks for equal ones at once and keeps only pairs. An itemset is left out as soon as it has met whom it can
be combined with. Memory follows the group and not the number of transactions times itemsets.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..families import Covering, Family
from ..families.base import scramble
from .vertical import BLOCK, Store, block_matrix

#: Cells of a level that a task may hold as a whole; beyond, pairs are found group by group.
HELD = 1 << 22
#: Positions of a group at most, but for groups of one block.
GROUP = 1 << 16
#: Bytes of positions and bits of a group, roughly.
GROUP_BYTES = 1 << 26
#: Numbers that a task has at once in one array, but for single blocks.
AT_ONCE = 1 << 20
#: Pairs that are looked at together.
PAIRS = 1 << 18
#: Itemsets of a level for which a task remembers every pair that has not met.
MATRIX = 4096
#: Sets of agreeing itemsets that a task remembers.
SEEN = 200_000


def by_group(m: int, family: Family) -> bool:
    """Whether a level's keys are too many for a task, while those of one block are not."""
    if not isinstance(family, Covering):
        return False
    positions = family.facts.n + 2 * family.facts.A
    return m * family.b * family.cells > HELD >= m * family.cells and positions // family.b <= GROUP


def compatible(members: np.ndarray) -> np.ndarray:
    """Whether the union of two itemsets has one item more, for all of a level."""
    held = np.zeros((len(members), int(members.max(initial=0)) + 1), np.float32)
    held[np.arange(len(members))[:, None], members] = 1
    return held @ held.T == members.shape[1] - 1


def equal_keys(stored: np.ndarray, query: np.ndarray, marks: np.ndarray, seen: set) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Rows of stored and of query with equal keys in a table, and the table, first tables first; both are
    (itemsets, tables). marks has two random numbers of each row: rows that have already agreed, as a set, are left out."""
    k = len(stored)
    both = np.ascontiguousarray(np.concatenate([stored, query]).T)
    order = np.argsort(both, axis=1)
    ranked, width = np.take_along_axis(both, order, 1), both.shape[1]
    first = np.ones(ranked.shape, bool)
    first[:, 1:] = ranked[:, 1:] != ranked[:, :-1]
    order, first = order.ravel(), first.ravel()
    starts, run, left = np.nonzero(first)[0], np.cumsum(first) - 1, order < k
    s = np.add.reduceat(left.astype(np.int64), starts)
    q = np.diff(np.append(starts, len(order))) - s
    good = np.nonzero((s > 0) & (q > 0))[0]
    if not len(good):
        return
    x, y = (np.add.reduceat(mark[order], starts)[good] for mark in marks)
    by = np.lexsort((y, x))  # stable: of equal sets, the one in the first table comes first
    new = np.ones(len(by), bool)
    new[1:] = (x[by][1:] != x[by][:-1]) | (y[by][1:] != y[by][:-1])
    if len(seen) > SEEN:
        seen.clear()
    fresh = [i for i, key in zip(by[new].tolist(), zip(x[by[new]].tolist(), y[by[new]].tolist())) if key not in seen]
    seen.update(zip(x[fresh].tolist(), y[fresh].tolist()))
    take = np.zeros(len(starts), bool)
    take[good[fresh]] = True
    at_s, at_q = np.nonzero(left & take[run])[0], np.nonzero(~left & take[run])[0]
    begin, n = (np.cumsum(q * take) - q * take)[run[at_s]], q[run[at_s]]
    ends, lo = np.cumsum(n), 0
    while lo < len(at_s):
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + PAIRS, "right")))
        c = n[lo:hi]
        each = np.repeat(begin[lo:hi] - (np.cumsum(c) - c), c) + np.arange(c.sum())
        yield np.repeat(order[at_s[lo:hi]], c), order[at_q[each]] - k, np.repeat(at_s[lo:hi] // width, c)
        lo = hi


def fold(out: np.ndarray, on: np.ndarray, cell: np.ndarray, number: np.ndarray) -> None:
    """Adds the exclusive or of the numbers of set positions to their cells; positions come in order of cells."""
    if len(cell):
        starts = np.nonzero(np.concatenate([[True], np.diff(cell) > 0]))[0]
        out[:, cell[starts]] ^= np.bitwise_xor.reduceat(np.where(on, number, np.uint64(0)), starts, axis=1)


def meet(family: Covering, members: np.ndarray, supports: np.ndarray, lo: int, hi: int, pos: np.ndarray, bits: np.ndarray, directions: bool) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Stored itemset, query itemset and table of the compatible pairs that meet in the family's blocks lo to hi - 1.

    pos has all positions of these blocks, paddings too, and -1 where a column of bits stands for none; bits are packed, one row
    for each item that members names. A pair comes with the first of these tables; without directions, one of both ways may do.
    """
    m, cells, facts = len(members), family.cells, family.facts
    at = np.nonzero(pos >= 0)[0]
    cell, number = family.places(pos[at])
    order = np.argsort(cell, kind="stable")
    at, cell, number = at[order], cell[order], number[order]
    pos = pos[at]
    unmet, seen = compatible(members) if m <= MATRIX else None, set()
    marks = np.stack([scramble(np.arange(2 * m), seed) for seed in (11, 12)])
    sides = [family.reach(supports, side) for side in ("stored", "query")]
    j, step = lo, 1
    rows = cols = np.arange(m)
    while j < hi:
        if unmet is not None:
            rows, cols = np.nonzero(unmet.any(1))[0], np.nonzero(unmet.any(0))[0]
            if not len(rows):
                return
        both = np.union1d(rows, cols)
        until = min(hi, j + max(1, min(step, AT_ONCE // (len(both) * cells))))
        begin, end = np.searchsorted(cell, (j * cells, until * cells))
        common, *x = (np.zeros((len(both), (until - j) * cells), np.uint64) for _ in range(3))
        tile = max(1, AT_ONCE // max(len(both), len(bits)))
        for b in range(begin, end, tile):
            p, c, z, col = (v[b : min(end, b + tile)] for v in (pos, cell - j * cells, number, at))
            own = p < facts.n
            there = (bits[:, col[own] >> 3] >> (col[own] & 7).astype(np.uint8)) & 1
            on = there[members[both, 0]]
            for i in range(1, members.shape[1]):
                on &= there[members[both, i]]
            fold(common, on > 0, c[own], z[own])
            for mine, (start, ones) in zip(x, sides):
                pad = (p >= start) & (p < start + facts.A)
                fold(mine, p[pad] - start < ones[both][:, None], c[pad], z[pad])
        keys = [family.keys_of((common ^ mine).reshape(len(both), until - j, cells)).reshape(len(both), -1) for mine in x]
        stored, query = keys[0][np.searchsorted(both, rows)], keys[1][np.searchsorted(both, cols)]
        for a, q, t in equal_keys(stored, query, np.concatenate([marks[:, rows], marks[:, m + cols]], axis=1), seen):
            a, q = rows[a], cols[q]
            if unmet is not None:
                new = unmet[a, q]
            else:
                new = (members[a][:, :, None] == members[q][:, None, :]).sum((1, 2)) == members.shape[1] - 1
            a, q, t = a[new], q[new], t[new] + j * (cells - 1)
            first = np.unique(a * m + q, return_index=True)[1]
            a, q, t = a[first], q[first], t[first]
            if unmet is not None:
                unmet[a, q] = False
                if not directions:
                    unmet[q, a] = False
            if len(a):
                yield a, q, t
        j, step = until, 2 * step


def groups_of(family: Covering, items: int, positions: int) -> int:
    most = max(1, min(GROUP, GROUP_BYTES // (8 + items // 8)))
    return max(1, min(family.b, -(-positions // most)))


def dealt(family: Covering, groups: int, pos: np.ndarray, bits: np.ndarray | None) -> pa.RecordBatch:
    """g, pos, bits: positions by group, and the items' bits of these; a group's columns begin at a whole byte."""
    g = family.places(pos)[0] // family.cells * groups // family.b
    order = np.argsort(g, kind="stable")
    names, start, count = np.unique(g[order], return_index=True, return_counts=True)
    wide = -(-count // 8) * 8
    begin = np.cumsum(wide) - wide
    to = np.repeat(begin - start, count) + np.arange(len(pos))
    there = np.full(int(wide.sum()), -1, np.int64)
    there[to] = pos[order]
    out = np.zeros((0 if bits is None else len(bits), len(there) // 8), np.uint8)
    for lo in range(0, len(out), 64):
        some = np.zeros((min(64, len(out) - lo), len(there)), np.uint8)
        some[:, to] = np.unpackbits(bits[lo : lo + 64], axis=1, bitorder="little")[:, order]
        out[lo : lo + 64] = np.packbits(some, axis=1, bitorder="little")
    cuts = [(int(b), int(b + w)) for b, w in zip(begin, wide)]
    columns = [pa.array(names, pa.int64()), pa.array([there[b:e].tobytes() for b, e in cuts], pa.binary()), pa.array([out[:, b // 8 : e // 8].tobytes() for b, e in cuts], pa.binary())]
    return pa.RecordBatch.from_arrays(columns, names=["g", "pos", "bits"])


def meetings(members: np.ndarray, supports: np.ndarray, store: Store, family: Covering, directions: bool = False) -> DataFrame:
    """a, q, table_no: numbers of the stored and of the query itemset of compatible pairs that meet, and the first table where they do."""
    spark, items = store.spark, len(store.labels)
    used, local = np.unique(members, return_inverse=True)
    local = local.reshape(members.shape)
    ones = {side: family.reach(supports, side) for side in ("stored", "query")}
    longest = {side: int(x.max(initial=0)) for side, (_, x) in ones.items()}
    groups = groups_of(family, len(used), family.facts.n + sum(longest.values()))
    shared = spark.sparkContext.broadcast((used, local, supports, family))
    schema = "g long, pos binary, bits binary"

    def transactions(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, _, _, fam = shared.value
        for batch in batches:
            for i in range(batch.num_rows):
                block, own, bits = (c[i].as_py() for c in batch.columns)
                pos = fam.transactions(block)
                yield dealt(fam, groups, pos, block_matrix(own, bits, items)[names])

    def padding(side: str):  # noqa: ANN202
        start, most = ones[side][0], longest[side]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            fam = shared.value[3]
            for batch in batches:
                for k in batch.column(0).to_pylist():
                    yield dealt(fam, groups, np.arange(start + k * BLOCK, start + min(most, (k + 1) * BLOCK)), None)

        return spark.range(-(-most // BLOCK)).mapInArrow(run, schema)

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, x, s, fam = shared.value
        pos, bits, g = [], [], None
        for batch in batches:
            for i in range(batch.num_rows):
                g, p, b = (batch.column(c)[i].as_py() for c in ("g", "pos", "bits"))
                p = np.frombuffer(p, np.int64)
                pos.append(p)
                bits.append(np.frombuffer(b, np.uint8).reshape(len(names), -1) if b else np.zeros((len(names), len(p) // 8), np.uint8))
        lo, hi = -(-g * fam.b // groups), -(-(g + 1) * fam.b // groups)
        for met in meet(fam, x, s, lo, hi, np.concatenate(pos), np.concatenate(bits, axis=1), directions):
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in met], names=["a", "q", "table_no"])

    # Blocks of the family without any position have equal keys everywhere, so every group has a row.
    rows = spark.range(groups).selectExpr("id AS g", "X'' AS pos", "X'' AS bits").unionByName(store.blocks.select("block", "items", "bits").mapInArrow(transactions, schema))
    for side, most in longest.items():
        if most:
            rows = rows.unionByName(padding(side))
    found = rows.repartition(min(groups, 1024), "g").groupBy("g").applyInArrow(find, "a long, q long, table_no long")
    return found.groupBy("a", "q").agg(F.min("table_no").alias("table_no"))
