"""Distinct pairs of members that share a key, made where they are kept apart: no pair is written or sent before it is a result."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

POSTINGS = 2_000_000  # rows (key, member) of one task
MEMBERS = 65_536  # members of one block
CELLS = 1 << 23  # possible pairs that a task looks at together
BATCH = 1 << 16  # pairs of one batch

_MIX = tuple(np.uint64(v) for v in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F))


def _mixed(m: np.ndarray, k: np.uint64) -> np.ndarray:
    """Well spread 64 bits of each member."""
    h = m.view(np.uint64) * k + k
    h = (h ^ (h >> np.uint64(29))) * _MIX[0]
    h = (h ^ (h >> np.uint64(32))) * _MIX[1]
    return h ^ (h >> np.uint64(31))


def grouped(key: np.ndarray, member: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(members, where each key's begin, and the end): sorted, repeats and keys of one member left out."""
    order = np.lexsort((member, key))
    key, member = key[order], member[order]
    new = np.ones(len(key), bool)
    new[1:] = (key[1:] != key[:-1]) | (member[1:] != member[:-1])
    key, member = key[new], member[new]
    head = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
    n = np.diff(np.append(head, len(key)))
    member, n = member[np.repeat(n > 1, n)], n[n > 1]
    return member, np.concatenate([[0], np.cumsum(n)])


def _sets(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row for each key of two or more members: a 128-bit signature of them and themselves."""
    got = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in it if b.num_rows]
    if not got:
        return
    member, ptr = grouped(*(np.concatenate(c) for c in zip(*got)))
    del got
    if len(ptr) < 2:
        return
    s1, s2 = (np.add.reduceat(_mixed(member, k), ptr[:-1]).view(np.int64) for k in _MIX)
    first = np.sort(np.unique(np.stack([s1, s2]), axis=1, return_index=True)[1])
    for at in range(0, len(first), 4096):
        some = first[at : at + 4096]
        yield pa.RecordBatch.from_arrays([pa.array(s1[some]), pa.array(s2[some]), pa.array([member[ptr[i] : ptr[i + 1]].tobytes() for i in some.tolist()], pa.binary())], names=["s1", "s2", "m"])


def _deal(blocks: int):  # noqa: ANN202
    """Sets of the same members once (their rows follow each other), cut in blocks; a row for each pair of a set's blocks, the right side empty where both are one."""

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = None
        out: tuple[list, list, list] = ([], [], [])
        held = 0
        for b in it:
            for s1, s2, m in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2)):
                if (s1, s2) == seen:
                    continue
                seen = s1, s2
                member = np.frombuffer(m.as_buffer(), np.int64)
                block = (_mixed(member, _MIX[1]) % np.uint64(blocks)).astype(np.int64)
                order = np.argsort(block, kind="stable")
                own, at = np.unique(block[order], return_index=True)
                lists = list(zip(own.tolist(), (x.tobytes() for x in np.split(member[order], at[1:]))))
                for k, (i, left) in enumerate(lists):
                    for j, right in [(i, b""), *lists[k + 1 :]]:
                        if i == j and len(left) == 8:
                            continue
                        out[0].append(i * blocks + j)
                        out[1].append(left)
                        out[2].append(right)
                        held += len(left) + len(right)
                        if held > 1 << 22 or len(out[0]) >= 8192:
                            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int32()), pa.array(out[1], pa.binary()), pa.array(out[2], pa.binary())], names=["p", "l", "r"])
                            out, held = ([], [], []), 0
        if out[0]:
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int32()), pa.array(out[1], pa.binary()), pa.array(out[2], pa.binary())], names=["p", "l", "r"])

    return run


def _lists(parts: list[pa.Array]) -> tuple[np.ndarray, np.ndarray]:
    """(members, where each row's begin, and the end) of binary columns."""
    flat, sizes = [], []
    for a in parts:
        ends = np.frombuffer(a.buffers()[1], np.int32)[a.offset : a.offset + len(a) + 1]
        if a.buffers()[2] is not None:
            flat.append(np.frombuffer(a.buffers()[2], np.uint8)[ends[0] : ends[-1]].copy().view(np.int64))
        sizes.append(np.diff(ends) // 8)
    return np.concatenate(flat or [np.zeros(0, np.int64)]), np.concatenate([[0], np.cumsum(np.concatenate(sizes))])


def _expanded(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """first[0], first[0] + 1, ... n[0] of them, then those of the next."""
    ends = np.cumsum(n)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(first - (ends - n), n)


def block_pairs(left: np.ndarray, lp: np.ndarray, right: np.ndarray, rp: np.ndarray, same: bool, cells: int = CELLS) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(left members, where the right members of each begin, and the end, right members) of distinct pairs that a row's left and right list hold;
    same: pairs of the left list, smaller first. Lists that hold much of the right
    side are bit strings that are combined, others are marked one by one."""
    a, at = np.unique(left, return_inverse=True)
    b, to = (a, at) if same else np.unique(right, return_inverse=True)
    rp = lp if same else rp
    size = np.diff(rp)
    by_row = np.argsort(at, kind="stable")
    row, of = at[by_row], np.repeat(np.arange(len(lp) - 1), np.diff(lp))[by_row]  # (left member, list), by member
    dense = size * 128 > len(b)
    number = np.cumsum(dense) - 1
    width = -(-len(b) // 64) * 8
    bits = np.zeros((int(dense.sum()), width), np.uint8)
    mark = np.zeros(width * 8, bool)
    for s in np.flatnonzero(dense).tolist():
        mark[to[rp[s] : rp[s + 1]]] = True
        bits[number[s]] = np.packbits(mark)
        mark[to[rp[s] : rp[s + 1]]] = False
    words = bits.view(np.uint64)
    high = max(1, cells // max(1, len(b)))
    for r0 in range(0, len(a), high):
        lo, hi = np.searchsorted(row, (r0, r0 + high))
        r, s = row[lo:hi] - r0, of[lo:hi]
        rows = min(high, len(a) - r0)
        thick = dense[s]
        some = np.zeros((rows, width // 8), np.uint64)
        rt, st = r[thick], number[s[thick]]
        ends = np.flatnonzero(np.concatenate([rt[1:] != rt[:-1], [True]])) + 1 if len(rt) else rt
        for x, k, end in zip(rt[ends - 1].tolist(), [0, *ends[:-1].tolist()], ends.tolist()):
            np.bitwise_or.reduce(words.take(st[k:end], axis=0), axis=0, out=some[x])
        r, s = r[~thick], s[~thick]
        ends = np.cumsum(size[s])
        if not len(rt) and len(ends) and ends[-1] * 32 < rows * len(b):  # few: sorted instead of marked
            hit = np.unique(np.repeat(r, size[s]) * (width * 8) + to[_expanded(rp[s], size[s])])
            x = hit // (width * 8)
            if same:
                up = hit - x * (width * 8) > x + r0
                hit, x = hit[up], x[up]
            count = np.bincount(x, minlength=rows)
        else:
            table = np.unpackbits(some.view(np.uint8), axis=1).ravel()
            k = 0
            while k < len(s):
                end = max(k + 1, int(np.searchsorted(ends, (ends[k - 1] if k else 0) + (cells >> 3), side="right")))
                table[np.repeat(r[k:end], size[s[k:end]]) * (width * 8) + to[_expanded(rp[s[k:end]], size[s[k:end]])]] = 1
                k = end
            table = table.view(bool).reshape(rows, width * 8)
            if same:
                for x in range(rows):
                    table[x, : r0 + x + 1] = False
            hit, count = np.flatnonzero(table), np.count_nonzero(table, axis=1)
        hit -= np.repeat(np.arange(rows) * (width * 8), count)
        ends = np.concatenate([[0], np.cumsum(count)])
        x = 0
        while x < rows:
            end = max(x + 1, int(np.searchsorted(ends, ends[x] + BATCH, side="right")) - 1)
            if ends[end] > ends[x]:
                yield a[x + r0 : end + r0], ends[x : end + 1] - ends[x], b[hit[ends[x] : ends[end]]]
            x = end


def _pairs(blocks: int, counted: bool = False):  # noqa: ANN202
    """Rows (member, its larger partners); counted: (member, its partners' number) instead, summed over some of the pairs."""

    def rows(found: Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
        for a, ptr, b in found:
            if counted:
                own, n = np.unique(b, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([a, own])), pa.array(np.concatenate([np.diff(ptr), n]))], names=["a", "n"])
            else:
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.ListArray.from_arrays(pa.array(ptr, pa.int32()), pa.array(b))], names=["a", "m"])

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple[list, list] = ([], [])
        now = -1

        def done() -> Iterator[pa.RecordBatch]:
            if held[0]:
                yield from rows(block_pairs(*_lists(held[0]), *_lists(held[1]), now // blocks == now % blocks))

        for batch in it:
            p = batch.column(0).to_numpy()
            cut = [0, *(np.flatnonzero(p[1:] != p[:-1]) + 1).tolist(), len(p)]
            for lo, hi in zip(cut, cut[1:]):
                if lo == hi:
                    continue
                if p[lo] != now:
                    yield from done()
                    held, now = ([], []), int(p[lo])
                held[0].append(batch.column(1).slice(lo, hi - lo))
                held[1].append(batch.column(2).slice(lo, hi - lo))
        yield from done()

    return run


def _found(postings: DataFrame, rows: int, members: int, blocks: int | None, counted: bool) -> DataFrame:
    cores = postings.sparkSession.sparkContext.defaultParallelism
    tasks = max(cores, math.ceil(rows / POSTINGS))
    blocks = blocks or max(math.ceil(members / MEMBERS), min(8, math.ceil(members / 1024)), 1)
    sets = postings.select(F.col("key").cast("long"), F.col("member").cast("long")).where("key is not null and member is not null").repartition(tasks, "key").mapInArrow(_sets, "s1 long, s2 long, m binary")
    dealt = sets.repartition(tasks, "s1").sortWithinPartitions("s1", "s2").mapInArrow(_deal(blocks), "p int, l binary, r binary")
    pairs = blocks * (blocks + 1) // 2
    return dealt.repartition(min(max(pairs, 1), 100_000), "p").sortWithinPartitions("p").mapInArrow(_pairs(blocks, counted), "a long, n long" if counted else "a long, m array<long>")


def pairs_within(postings: DataFrame, rows: int, members: int, blocks: int | None = None) -> DataFrame:
    """(src, dst): distinct pairs of members of one key, src < dst, of postings(key, member). rows and members are about how many there are.

    Keys are 64 bits; those with the same members count once. Members lie in hash blocks, and a
    pair of blocks finds its pairs in one task, so a pair that many keys give
    is neither written nor sent. A key's members, 8 bytes each, pass one task.
    """
    found = _found(postings, rows, members, blocks, False)
    return found.select("a", F.explode("m").alias("b")).select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"))


def degrees_within(postings: DataFrame, rows: int, members: int, blocks: int | None = None) -> DataFrame:
    """(node, degree) of the pairs of pairs_within(): the same pairs are made and counted in their task, and none leaves it."""
    return _found(postings, rows, members, blocks, True).groupBy(F.col("a").alias("node")).agg(F.sum("n").alias("degree"))
