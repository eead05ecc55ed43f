"""Removal of byte strings that repeat across documents, by suffix sorting with linear grouping.

A byte goes if a 50-byte string over it also starts in a document with a
smaller doc_id. Strings are judged on the input.

Whole texts are laid in batches. Each 50-byte window has an anchor, the least
hash among its 24-byte strings, so equal windows have equal anchors, and a
run of windows with one anchor forms a context. Batches and hash buckets
exchange packed arrays (a few rows a batch, no row for each window):

1. buckets learn which anchors occur in several documents, and the smallest
   document of each context. A context that a smaller document has too is
   settled. A context whose anchor also stands in other contexts is open;
2. open contexts meet by anchor. A hash of windows prunes those that cannot
   repeat; equal strings collapse; the suffixes of what is left are sorted by
   linear grouping, and equal neighbours of 50 bytes form classes. A class's
   smallest document settles its windows;
3. batches turn settled windows into removed bytes.

Contexts collapse per batch before they are sent, so a passage in a third of
all documents sends one entry a batch. An anchor with over HOT open contexts
is settled by aggregating its windows instead.

Edge cases: null text counts as empty; texts under 50 bytes lose nothing;
documents with one doc_id are not smaller than each other; a null doc_id
counts as larger than any; an empty table gives no rows; only the id and text
columns are read.
"""

from __future__ import annotations

import hashlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, functions as F

from ..plans.storage import stash, stash_path

WIDTH = 50
GRAM = 24
BATCH_BYTES = 4 << 20
BUCKET_ENTRIES = 1_500_000
HOT = 20_000  # open contexts of one anchor that one task settles
BLOCK_BYTES = 128 << 10  # strings sorted at a time: small lists stay in the processor's cache
CHUNK = 1 << 16  # windows whose anchors are found at a time
LAST = np.iinfo(np.int64).max

# ---------------------------------------------------------------- suffix sorting


def suffix_array(text: bytes | list[int]) -> list[int]:
    """Suffixes of text in order, by grouping on Lyndon prefixes.

    First phase: groups of suffixes, highest first. Each suffix of a group
    finds its previous smaller-group suffix; those move to new groups right
    after their own, the more followers the higher. Second phase: from the
    smallest suffix on, the suffix before a placed one, and its chain of
    previous-smaller suffixes, take the next free place of their groups.
    """
    n = len(text) + 1
    first = sorted(range(n - 1), key=text.__getitem__)
    order = [n - 1, *first]  # the end of the text is the smallest suffix
    at = [0] * n
    group = [0] * n
    size = [0] * (n + 1)
    start, before = 0, None
    for i, s in enumerate(order):
        here = text[s] if s < n - 1 else None
        if i == 0 or here != before:
            start, before = i, here
        at[s], group[s] = i, start
        size[start] += 1
    prev = [-1] * n

    end = n - 1
    while end >= 0:
        low = group[order[end]]
        members = order[low : end + 1] if low == end else sorted(order[low : end + 1])
        followers: dict[int, int] = {}
        for s in members:
            p = s - 1
            while p >= 0 and group[p] >= low:
                p = prev[p]
            prev[s] = p
            if p >= 0:
                followers[p] = followers.get(p, 0) + 1
        if followers:
            if len(followers) == 1:
                rounds = [list(followers)]
            else:
                by: dict[int, list[int]] = defaultdict(list)
                for p, k in followers.items():
                    by[k].append(p)
                rounds = [by[k] for k in sorted(by, reverse=True)]
            for ps in rounds:
                moved: dict[int, int] = {}
                for p in ps:  # to the end of its group
                    g = group[p]
                    size[g] -= 1
                    e = g + size[g]
                    q, here = order[e], at[p]
                    order[e], order[here] = p, q
                    at[p], at[q] = e, here
                    moved[g] = moved.get(g, 0) + 1
                for p in ps:
                    g = group[p]
                    new = g + size[g]
                    if new == g:  # the whole group moved: it stays as it is
                        size[g] = moved.pop(g, size[g])
                    elif g in moved:
                        size[new] = moved.pop(g)
                    if at[p] >= new:
                        group[p] = new
        end = low - 1

    out = [-1] * n
    out[0] = n - 1
    free = list(range(n))
    done = bytearray(n)
    done[n - 1] = 1
    for i in range(n):
        s = out[i] - 1
        while s >= 0 and not done[s]:
            g = group[s]
            out[free[g]] = s
            free[g] += 1
            done[s] = 1
            s = prev[s]
    return out[1:]


# ---------------------------------------------------------------- anchors of a batch

_RNG = np.random.default_rng(20)
_BYTE = _RNG.integers(0, 1 << 63, 256, dtype=np.int64).astype(np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_BACK = np.uint64(pow(int(_BASE), -1, 1 << 64))
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    size = 1 << max(17, (n + 1).bit_length())
    if size not in _powers:
        if len(_powers) > 3:
            _powers.clear()
        one = np.ones(1, np.uint64)
        _powers[size] = tuple(np.cumprod(np.concatenate([one, np.full(size - 1, b, np.uint64)]), dtype=np.uint64) for b in (_BASE, _BACK))
    return _powers[size]


def _mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> np.uint64(31))
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xA0761D6478BD642F)
    return h ^ (h >> np.uint64(32))


def prefix_sums(raw: np.ndarray) -> np.ndarray:
    up, _ = _power(len(raw))
    out = np.zeros(len(raw) + 1, np.uint64)
    np.cumsum(_BYTE[raw] * up[: len(raw)], out=out[1:])
    return out


def slice_hash(sums: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of the byte ranges [start, end)."""
    _, back = _power(len(sums) - 1)
    return _mix((sums[end] - sums[start]) * back[start] + (end - start).astype(np.uint64))


class Runs:
    """The contexts of a batch: windows lo..hi (starts) with one anchor, and the entries they collapse to."""

    def __init__(self, blob: bytes, lengths: np.ndarray, ids: np.ndarray) -> None:
        raw = np.frombuffer(blob, np.uint8)
        ends = np.cumsum(lengths)
        begins = ends - lengths
        empty = np.zeros(0, np.int64)
        self.raw, self.begins, self.ends, self.ids = raw, begins, ends, ids
        self.lo = self.hi = self.doc = self.entry = empty
        self.anchor = self.context = np.zeros(0, np.uint64)
        self.first_id = self.first_run = empty
        if len(raw) < WIDTH:
            return
        n = len(raw) - WIDTH + 1
        doc = np.repeat(np.arange(len(lengths), dtype=np.int32), lengths)[:n]
        found: list[tuple[np.ndarray, ...]] = []
        for at in range(0, n, CHUNK):  # arrays that stay in the processor's cache
            found.append(self._chunk(raw[at : at + CHUNK + WIDTH - 1], doc[at : at + CHUNK], at, ends))
        self.lo, self.hi, self.anchor, self.context = (np.concatenate(c) for c in zip(*found))
        self.doc = doc[self.lo].astype(np.int64)
        own = ids[self.doc]
        order = np.lexsort((own, self.context, self.anchor))
        a, c = self.anchor[order], self.context[order]
        head = np.ones(len(order), bool)
        head[1:] = (a[1:] != a[:-1]) | (c[1:] != c[:-1])
        self.entry = np.empty(len(order), np.int64)
        self.entry[order] = np.cumsum(head) - 1
        self.first_run = order[head]
        self.first_id = own[self.first_run]


    @staticmethod
    def _chunk(raw: np.ndarray, doc: np.ndarray, base: int, ends: np.ndarray) -> tuple[np.ndarray, ...]:
        """Runs of the windows that start in one chunk: (lo, hi, anchor, context)."""
        n = len(doc)
        sums = prefix_sums(raw)
        _, back = _power(len(raw))
        grams = len(raw) - GRAM + 1
        least, span, wide = _mix((sums[GRAM:] - sums[:grams]) * back[:grams]), 1, WIDTH - GRAM + 1
        while span * 2 <= wide:
            least = np.minimum(least[:-span], least[span:])
            span *= 2
        least = np.minimum(least[:n], least[wide - span : wide - span + n])
        new = np.ones(n, bool)
        new[1:] = (least[1:] != least[:-1]) | (doc[1:] != doc[:-1])
        new[::512] = True  # very repetitive text: no context grows without bound
        begin = np.flatnonzero(new)
        # a run's windows are of one document; those that would cross its end are no windows
        last = np.minimum(np.append(begin[1:], n) - 1, ends[doc[begin]] - WIDTH - base)
        begin, last = begin[last >= begin], last[last >= begin]
        return begin + base, last + base, least[begin], slice_hash(sums, begin, last + WIDTH)


def _blobs(docs: DataFrame) -> Iterator:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, nth = TaskContext.get().partitionId(), 0
        ids: list = []
        texts: list[bytes] = []
        held = 0

        def made() -> pa.RecordBatch:
            nonlocal nth, held
            row = [[(part << 32) + nth], [ids.copy()], [list(map(len, texts))], [b"".join(texts)]]
            nth, held = nth + 1, 0
            ids.clear()
            texts.clear()
            return pa.RecordBatch.from_arrays([pa.array(r, k) for r, k in zip(row, (pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary()))], names=["batch", "ids", "lengths", "blob"])

        for b in batches:
            for key, t in zip(b.column(0).to_pylist(), b.column(1)):
                raw = (t.as_py() or "").encode("utf-8", "surrogatepass")
                if texts and held + len(raw) > BATCH_BYTES:
                    yield made()
                ids.append(key)
                texts.append(raw)
                held += len(raw)
        if texts:
            yield made()

    return docs.mapInArrow(run, "batch long, ids array<long>, lengths array<long>, blob binary")


def _runs_of(b: pa.RecordBatch, i: int) -> Runs:
    ids = np.array([LAST if v is None else v for v in b.column("ids")[i].as_py()], np.int64)
    return Runs(b.column("blob")[i].as_buffer().to_pybytes() if b.column("blob")[i].is_valid else b"", np.array(b.column("lengths")[i].as_py(), np.int64), ids)


def _sent(buckets: int):  # noqa: ANN202
    """Step 1, batches: entries dealt to buckets."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                r = _runs_of(b, i)
                to = (_mix(r.anchor[r.first_run] + np.uint64(5)) % np.uint64(buckets)).astype(np.int64)
                order = np.argsort(to, kind="stable")
                cut = np.searchsorted(to[order], np.arange(buckets + 1))
                rows: list[list] = [[], [], [], [], [], []]
                for k in np.flatnonzero(np.diff(cut)).tolist():
                    at = order[cut[k] : cut[k + 1]]
                    f = r.first_run[at]
                    for o, v in zip(rows, (k, b.column("batch")[i].as_py(), at.astype(np.int32).tobytes(), r.anchor[f].tobytes(), r.context[f].tobytes(), r.first_id[at].tobytes())):
                        o.append(v)
                yield pa.RecordBatch.from_arrays([pa.array(o, k) for o, k in zip(rows, (pa.int32(), pa.int64(), *[pa.binary()] * 4))], names=["bucket", "batch", "at", "anchor", "context", "id"])

    return run, "bucket int, batch long, at binary, anchor binary, context binary, id binary"


def _meet(t: pa.Table) -> pa.Table:
    """Step 1, buckets: what each entry needs to know."""
    joined = lambda c, kind: np.frombuffer(b"".join(t.column(c).to_pylist()), kind)
    anchor, context, own, at = joined("anchor", np.uint64), joined("context", np.uint64), joined("id", np.int64), joined("at", np.int32)
    count = np.array([len(v) // 4 for v in t.column("at").to_pylist()])
    row = np.repeat(np.arange(len(count)), count)
    order = np.argsort(anchor, kind="stable")
    a = anchor[order]
    same = np.zeros(len(a), bool)
    same[1:] = a[1:] == a[:-1]
    several = same.copy()
    several[:-1] |= same[1:]
    sub = order[several]
    sub = sub[np.lexsort((own[sub], context[sub], anchor[sub]))]
    a, c, o = anchor[sub], context[sub], own[sub]
    head = np.ones(len(sub), bool)
    head[1:] = a[1:] != a[:-1]
    chead = head.copy()
    chead[1:] |= c[1:] != c[:-1]
    gid, cid = np.cumsum(head) - 1, np.cumsum(chead) - 1
    groups = int(gid[-1]) + 1 if len(gid) else 0
    low, high = np.full(groups, LAST), np.full(groups, np.iinfo(np.int64).min)
    np.minimum.at(low, gid, o)
    np.maximum.at(high, gid, o)
    kinds = np.bincount(gid[chead], minlength=groups)
    least = o[chead][cid]
    useful = (low < high)[gid]
    is_open = (kinds > 1)[gid]
    sub, least, is_open = sub[useful], least[useful], is_open[useful]
    by = np.argsort(row[sub], kind="stable")
    sub, least, is_open = sub[by], least[by], is_open[by]
    cut = np.searchsorted(row[sub], np.arange(len(count) + 1))
    out: list[list] = [[], [], [], []]
    ids = t.column("batch").to_pylist()
    for k in np.flatnonzero(np.diff(cut)).tolist():
        s = slice(cut[k], cut[k + 1])
        for x, v in zip(out, (ids[k], at[sub[s]].tobytes(), least[s].tobytes(), is_open[s].astype(np.uint8).tobytes())):
            x.append(v)
    return pa.table([pa.array(x, k) for x, k in zip(out, (pa.int64(), *[pa.binary()] * 3))], names=["batch", "at", "least", "open"])


_TOLD = "batch long, at binary, least binary, open binary"


def _settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Step 2, batches: open contexts that this batch holds first, with their bytes; and one row (at -1) of what is settled."""
    for b in batches:
        for i in range(b.num_rows):
            r = _runs_of(b, i)
            least, is_open = _answers(b.column("told")[i].as_py() or [], r)
            own, low = r.ids[r.doc], least[r.entry]
            whole = low < own
            gone = _merged(r.lo[whole], r.hi[whole] + WIDTH, len(r.raw))
            mine = is_open & (least == r.first_id)
            waits = np.flatnonzero(mine[r.entry] & ~whole & (own == low))
            state = np.concatenate([[len(gone)], gone.ravel(), r.entry[waits], r.lo[waits]]).astype("<i8").tobytes()
            batch = b.column("batch")[i].as_py()
            rows: list[list] = [[0], [batch], [-1], [0], [state]]
            blob = r.raw.tobytes()
            for e in np.flatnonzero(mine).tolist():
                f = r.first_run[e]
                for x, v in zip(rows, (int(r.anchor[f].astype(np.int64)), batch, e, int(least[e]), blob[r.lo[f] : r.hi[f] + WIDTH])):
                    x.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(rows, (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.binary()))], names=["anchor", "batch", "at", "id", "bytes"])


_OPEN = "anchor long, batch long, at int, id long, bytes binary"


def _merged(starts: np.ndarray, ends: np.ndarray, n: int) -> np.ndarray:
    """Disjoint (start, end) rows that cover the same places."""
    d = np.bincount(starts, minlength=n + 1) - np.bincount(ends, minlength=n + 1) if len(starts) else np.zeros(n + 1, np.int64)
    on = np.concatenate([[False], np.cumsum(d)[:-1] > 0, [False]])
    return np.flatnonzero(on[1:] != on[:-1]).reshape(-1, 2)


def _answers(told: list[dict], r: Runs) -> tuple[np.ndarray, np.ndarray]:
    """By entry: the smallest document of its context, and whether its anchor stands in other contexts too."""
    least, is_open = r.first_id.copy(), np.zeros(len(r.first_id), bool)
    for x in told:
        at = np.frombuffer(x["at"], np.int32)
        least[at] = np.frombuffer(x["least"], np.int64)
        is_open[at] = np.frombuffer(x["open"], np.uint8) > 0
    return least, is_open


def settle_block(anchor: np.ndarray, ids: np.ndarray, strings: list[bytes]) -> list[np.ndarray]:
    """For each string, which of its windows also stand in a string of the same anchor with a smaller id."""
    sizes = np.fromiter(map(len, strings), np.int64, len(strings))
    flags = [np.zeros(max(0, n - WIDTH + 1), bool) for n in sizes.tolist()]
    raw = np.frombuffer(b"".join(strings), np.uint8)
    if len(raw) < WIDTH:
        return flags
    ends = np.cumsum(sizes)
    begins = ends - sizes
    of = np.repeat(np.arange(len(strings)), np.maximum(sizes - WIDTH + 1, 0))
    first = np.cumsum(np.maximum(sizes - WIDTH + 1, 0)) - np.maximum(sizes - WIDTH + 1, 0)
    w = begins[of] + np.arange(len(of)) - first[of]
    h = slice_hash(prefix_sums(raw), w, w + WIDTH)
    # pruning: a window whose hash no other id has cannot be in a class of two documents
    order = np.lexsort((ids[of], h))
    hs, own = h[order], ids[of][order]
    head = np.ones(len(hs), bool)
    head[1:] = hs[1:] != hs[:-1]
    cls = np.cumsum(head) - 1
    tail = np.ones(len(hs), bool)
    tail[:-1] = head[1:]
    mixed = own[head] < own[tail]
    maybe = np.zeros(len(of), bool)
    maybe[order] = mixed[cls]
    # maximal runs of such windows that stand equally often, equal ones once
    often = np.zeros(len(of), np.int64)
    often[order] = np.bincount(cls)[cls]
    joins = maybe[1:] & maybe[:-1] & (of[1:] == of[:-1]) & (often[1:] == often[:-1])
    starts = np.flatnonzero(maybe & ~np.concatenate([[False], joins]))
    stops = np.flatnonzero(maybe & ~np.concatenate([joins, [False]]))
    whole = raw.tobytes()
    pieces: dict[bytes, list[tuple[int, int]]] = defaultdict(list)
    for s, e in zip(starts.tolist(), stops.tolist()):
        pieces[whole[w[s] : w[e] + WIDTH]].append((s, e))
    # a piece none of whose windows stands in another piece is a class of its own: its smallest id settles it
    piece = np.full(len(of), -1)
    for k, at in enumerate(pieces.values()):
        for s, e in at:
            piece[s : e + 1] = k
    heads = np.flatnonzero(head)
    ps = piece[order]
    mixed = np.minimum.reduceat(ps, heads) != np.maximum.reduceat(ps, heads)
    shared = np.zeros(len(pieces), bool)
    at = mixed[cls] & (ps >= 0)
    shared[ps[at]] = True
    texts = []
    for k, (t, at) in enumerate(list(pieces.items())):
        if shared[k]:
            texts.append(t)
            continue
        low = min(int(ids[of[s]]) for s, _ in at)
        for s, e in at:
            flags[of[s]][s - first[of[s]] : e + 1 - first[of[s]]] |= low < ids[of[s]]
    if not texts:
        return flags
    least = [min(int(ids[of[s]]) for s, _ in pieces[t]) for t in texts]
    # suffixes of the distinct strings in order; a 0 byte may stand in a text, so bytes are raised by one and 0 divides
    flat = np.zeros(sum(map(len, texts)) + len(texts), np.int64)
    at, place = 0, []
    for t in texts:
        flat[at : at + len(t)] = np.frombuffer(t, np.uint8).astype(np.int64) + 1
        place.append(at)
        at += len(t) + 1
    order = np.array(suffix_array(flat.tolist()), np.int64)
    owner = np.full(len(flat), -1, np.int64)
    for k, (t, p) in enumerate(zip(texts, place)):
        owner[p : p + len(t) - WIDTH + 1] = k
    order = order[owner[order] >= 0]  # only suffixes with a whole window
    new = np.ones(len(order), bool)
    for lo in range(1, len(order), 50_000):
        x, y = order[lo - 1 : lo + 49_999], order[lo : lo + 50_000]
        grid = np.arange(WIDTH)
        new[lo : lo + 50_000] = (flat[x[: len(y), None] + grid] != flat[y[:, None] + grid]).any(axis=1)
    cls = np.cumsum(new) - 1
    low = np.full(int(cls[-1]) + 1, LAST)
    np.minimum.at(low, cls, np.array(least, np.int64)[owner[order]])
    best = np.full(len(flat), LAST)
    best[order] = low[cls]
    for t, p in zip(texts, place):
        got = best[p : p + len(t) - WIDTH + 1]
        for s, e in pieces[t]:
            k = of[s]
            flags[k][s - first[k] : e + 1 - first[k]] |= got < ids[k]
    return flags


def _classes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Step 2, anchors: rows come sorted by anchor; whole groups are settled together in blocks."""
    held: list[pa.Table] = []
    size = 0

    def settled(t: pa.Table) -> pa.RecordBatch:
        flags = settle_block(t.column("anchor").to_numpy(), t.column("id").to_numpy(), t.column("bytes").to_pylist())
        some = [k for k, f in enumerate(flags) if f.any()]
        pick = t.take(pa.array(some, pa.int64()))
        return pa.RecordBatch.from_arrays([pick.column("batch").combine_chunks(), pick.column("at").combine_chunks(), pa.array([np.packbits(flags[k]).tobytes() for k in some], pa.binary())], names=["batch", "at", "bits"])

    for b in batches:
        for lo in range(0, b.num_rows, 512):
            t = pa.Table.from_batches([b.slice(lo, 512)])
            held.append(t)
            size += t.column("bytes").nbytes
            if size < BLOCK_BYTES:
                continue
            t = pa.concat_tables(held).combine_chunks()
            a = t.column("anchor").to_numpy()
            cut = int(np.searchsorted(a, a[-1]))  # the last group may go on
            if cut:
                yield settled(t.slice(0, cut))
                t = t.slice(cut)
            held, size = [t], t.column("bytes").nbytes if t.num_rows else 0
    if held:
        t = pa.concat_tables(held).combine_chunks()
        if t.num_rows:
            yield settled(t)


def _hot_classes(hot: DataFrame) -> DataFrame:
    """The windows of anchors with very many open contexts, aggregated with map-side combine."""
    starts = F.sequence(F.lit(0), F.length("bytes") - WIDTH)
    windows = hot.select("batch", "at", "id", F.explode(starts).alias("k"), "bytes").withColumn("window", F.substring("bytes", F.col("k") + 1, WIDTH)).drop("bytes")
    low = windows.groupBy("window").agg(F.min("id").alias("low"))
    late = windows.join(low, "window").where("low < id")
    told = late.groupBy("batch", "at").agg(F.collect_list("k").alias("ks"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            bits = []
            for ks in b.column("ks").to_pylist():
                f = np.zeros(max(ks) + 1, bool)
                f[ks] = True
                bits.append(np.packbits(f).tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(bits, pa.binary())], names=["batch", "at", "bits"])

    return told.mapInArrow(run, "batch long, at int, bits binary")


def _removed(n: int, state: bytes, found: list[dict]) -> np.ndarray:
    """Which of the n bytes of a batch go."""
    v = np.frombuffer(state, "<i8")
    k = int(v[0])
    gone = v[1 : 1 + 2 * k].reshape(-1, 2)
    entry, lo = v[1 + 2 * k :].reshape(2, -1)
    starts, ends = [gone[:, 0]], [gone[:, 1]]
    if found and len(entry):
        bits = {x["at"]: np.flatnonzero(np.unpackbits(np.frombuffer(x["bits"], np.uint8))) for x in found}
        for e, at in zip(entry.tolist(), lo.tolist()):
            if e in bits:
                starts.append(bits[e] + at)
                ends.append(bits[e] + at + WIDTH)
    out = np.zeros(n, bool)
    for s, e in _merged(np.concatenate(starts), np.concatenate(ends), n).tolist():
        out[s:e] = True
    return out


def _finish(keep_text: bool):  # noqa: ANN202
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                blob = b.column("blob")[i].as_py() or b""
                gone = _removed(len(blob), b.column("state")[i].as_py(), b.column("found")[i].as_py() or [])
                rows: list[list] = [[] for _ in range(7)]
                raw = np.frombuffer(blob, np.uint8)
                keys = b.column("ids")[i].as_py()
                ends = np.cumsum(b.column("lengths")[i].as_py())
                for d, (s, e) in enumerate(zip([0, *ends[:-1].tolist()], ends.tolist())):
                    g = gone[s:e]
                    n = int(g.sum())
                    edge = np.flatnonzero(np.diff(np.concatenate([[False], g, [False]]).astype(np.int8)))
                    kept = blob[s:e] if not n else raw[s:e][~g].tobytes()
                    for x, v in zip(rows, (keys[d], e - s, n, len(edge) // 2, hashlib.sha256(kept).hexdigest(), edge.tolist(), kept if keep_text else None)):
                        x.append(v)
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.int64()), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(rows, kinds)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "edges", "kept"])

    return run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, edges array<long>, kept binary"


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep_text: bool = False) -> DataFrame:
    """One row per document: its size, removed bytes and spans (`edges`: start, end, start, end ...), and with keep_text the bytes that stay."""
    spark = docs.sparkSession
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    total = base.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = min(50_000, max(4, -(-total // (4 * BATCH_BYTES))))
    name = "suffix_" + stash_path(spark, "x").rsplit("-", 1)[1]
    # bucketed by batch: the later joins move only what is told to the batches, never their texts
    _blobs(base).write.bucketBy(parts, "batch").option("path", stash_path(spark, "blobs")).option("compression", "zstd").saveAsTable(name)
    blobs = spark.table(name)
    spark.sql(f"DROP TABLE {name}")  # the name only: the plan holds the files, whose folder goes with the session
    buckets = max(4, -(-total // 14 // BUCKET_ENTRIES))
    run, kind = _sent(buckets)
    told = stash(blobs.mapInArrow(run, kind).groupBy("bucket").applyInArrow(_meet, _TOLD), "told")
    told = told.groupBy("batch").agg(F.collect_list(F.struct("at", "least", "open")).alias("told"))
    informed = blobs.join(told.hint("shuffle_hash"), "batch", "left")
    settled = stash(informed.mapInArrow(_settle, _OPEN), "open")
    open_ = settled.where("at >= 0")
    states = settled.where("at < 0").select("batch", F.col("bytes").alias("state"))
    crowds = open_.groupBy("anchor").agg(F.count("*").alias("n")).where(F.col("n") > HOT).select("anchor")
    crowds = stash(crowds, "hot")
    cold = open_.join(crowds, "anchor", "left_anti")
    pieces = max(4, -(-total // (16 << 20)))
    found = cold.repartition(pieces, "anchor").sortWithinPartitions("anchor").mapInArrow(_classes, "batch long, at int, bits binary")
    if crowds.limit(1).count():
        found = found.unionByName(_hot_classes(open_.join(crowds, "anchor", "left_semi")))
    found = stash(found, "found").groupBy("batch").agg(F.collect_list(F.struct("at", "bits")).alias("found"))
    run, kind = _finish(keep_text)
    known = states.join(found, "batch", "left")
    return blobs.join(known.hint("shuffle_hash"), "batch").mapInArrow(run, kind)
