"""SimHash near-duplicate groups with pigeonring candidate pruning.

A document's 64-bit fingerprint is the bitwise majority over the XXH64 hashes
of its word shingles (multiset). Two fingerprints within `tau` bits are
linked. The 64 bits are laid on a ring of segments. If two fingerprints
differ in at most tau bits, then from some start segment every chain of l
consecutive segments differs in at most floor(l * tau / segments) bits. The
first links of that chain give equality keys (a budget of b bits over a
segment cut in b + 1 pieces leaves one piece equal); the whole chain prunes
the candidates before the full Hamming check.

Edge cases: null text counts as empty; a text without words has fingerprint
0 and is linked like any other; repeated rows stay repeated; null doc_id is
kept as a row and never becomes the id of a group that has other ids; only the id and text
columns are read, so extra columns cannot clash.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, functions as F

from ..operators.components import connected
from ..plans.storage import drop_stash, stash
from .memory import release, release_driver, tidy

SMALL = 64  # fingerprints of a bucket whose pairs are all told
BLOCK = 4096  # fingerprints of one candidate bucket that one task compares at a time
BUCKET_ENTRIES, HELD = 500_000, 200_000  # prefix shingles of one bucket, and those that a task packs together
MARK, WIDE = 1024, 8192  # bits of the bitmaps that rows of a bucket carry, for texts of up to 2 * MARK shingles and for longer ones; MARK is the least of any
SAMPLE, RANKED = 10_000, 50_000  # texts read for the order of shingles, and shingles whose rank is sent to the tasks


def fingerprint(text: str | None, words_per_shingle: int = 3, seed: int = 42) -> int:
    """Unsigned 64-bit majority fingerprint of one text."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    k = min(words_per_shingle, len(words))
    size = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(size + 1) - 1
    starts = (ends - size)[: len(words) - k + 1].tolist()
    digest = xxhash.xxh64_intdigest
    ones, n = np.zeros(64, np.int64), len(starts)
    ends = ends[k - 1 :].tolist()
    for at in range(0, n, 65_536):  # bounded memory for very long texts
        h = np.array([digest(joined[s:e], seed) for s, e in zip(starts[at : at + 65_536], ends[at : at + 65_536])], ">u8")
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > n).tobytes(), "big")


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3) -> DataFrame:
    """(doc_id, fp): fp is the fingerprint as a signed long."""

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fp = np.array([fingerprint(t, words) for t in b.column(1).to_pylist()], np.uint64).astype(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0).cast(pa.int64()), pa.array(fp)], names=["doc_id", "fp"])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, fp long")


def ring(bits: int, segments: int) -> list[tuple[int, int]]:
    """(shift, width) of each segment, most significant first."""
    widths = [bits // segments + (i < bits % segments) for i in range(segments)]
    out, left = [], bits
    for w in widths:
        left -= w
        out.append((left, w))
    return out


def chain_keys(tau: int, segments: int, links: int) -> list[list[tuple[int, int]]]:
    """For each start segment and choice of equal pieces: the (shift, width) cells that a key is made of."""
    cells = ring(64, segments)
    keys: list[list[tuple[int, int]]] = []
    for start in range(segments):
        partial: list[list[tuple[int, int]]] = [[]]
        for link in range(links):
            shift, width = cells[(start + link) % segments]
            budget = (link + 1) * tau // segments
            if budget >= width:
                break
            parts = [(shift + s, w) for s, w in ring(width, budget + 1)]
            partial = [p + [piece] for p in partial for piece in parts]
        keys.extend(partial)
    return keys


def passes_ring(x: np.ndarray, tau: int, segments: int) -> np.ndarray:
    """Whether from some start every chain of segments of the difference x keeps its proportional budget."""
    diff = np.stack([np.bitwise_count((x >> np.uint64(s)) & np.uint64((1 << w) - 1)) for s, w in ring(64, segments)]).astype(np.int16)
    found = np.zeros(x.shape, bool)
    for start in range(segments):
        run, ok = np.zeros(x.shape, np.int16), np.ones(x.shape, bool)
        for link in range(segments):
            run += diff[(start + link) % segments]
            ok &= run <= (link + 1) * tau // segments
        found |= ok
    return found


def _forest(a: np.ndarray, b: np.ndarray, tau: int, segments: int) -> tuple[np.ndarray, np.ndarray]:
    """Links that connect what a bucket's links connect: at most one per fingerprint, plus those between its two blocks."""
    same = a is b
    nodes = a if same else np.unique(np.concatenate([a, b]))
    at = np.arange(len(nodes))
    at_a, at_b = (at, at) if same else (np.searchsorted(nodes, a), np.searchsorted(nodes, b))
    left: list[np.ndarray] = []
    right: list[np.ndarray] = []
    parent = at.copy()
    rows = max(1, 4_000_000 // max(1, len(b)))
    for lo in range(0, len(a), rows):
        x = a[lo : lo + rows, None] ^ b[None, :]
        i, j = np.nonzero(_near(x, tau, segments))
        i, j = at_a[i + lo], at_b[j]
        keep = i != j
        i, j = i[keep], j[keep]
        while len(i):  # hook larger roots on smaller ones until this block's links are inside trees
            ri, rj = parent[i], parent[j]
            open_ = ri != rj
            i, j, ri, rj = i[open_], j[open_], ri[open_], rj[open_]
            if not len(i):
                break
            hi, low = np.maximum(ri, rj), np.minimum(ri, rj)
            order = np.lexsort((low, hi))
            first = np.r_[True, hi[order][1:] != hi[order][:-1]]
            pick = order[first]
            parent[hi[pick]] = low[pick]
            left.append(nodes[i[pick]])
            right.append(nodes[j[pick]])
            while (parent != parent[parent]).any():
                parent = parent[parent]
    return (np.concatenate(left), np.concatenate(right)) if left else (nodes[:0], nodes[:0])


def _near(x: np.ndarray, tau: int, segments: int) -> np.ndarray:
    """Pigeonring pruning, then the full Hamming check, of a matrix of differences."""
    ok = np.bitwise_count(x & np.uint64(0xFFFFFFFF)) <= tau  # half of the ring can never exceed the whole budget
    i, j = np.nonzero(ok)
    y = x[i, j]
    good = passes_ring(y, tau, segments)
    good[good] = np.bitwise_count(y[good]) <= tau
    ok[i, j] = good
    return ok


def links(fps: DataFrame, tau: int = 3, segments: int = 4, chain: int = 2) -> DataFrame:
    """Links (src, dst) whose components are those of all fingerprint pairs within tau bits.

    fps(fp): distinct signed longs. Buckets of over BLOCK fingerprints are
    compared in pairs of blocks in separate tasks, so none is cut short.
    """
    fp = F.col("fp")
    keys = []
    for n, cells in enumerate(chain_keys(tau, segments, chain)):
        key = F.lit(0).cast("long")
        for shift, width in cells:
            key = key.bitwiseOR(F.lit(0)) * F.lit(1 << width) + F.shiftrightunsigned(fp, shift).bitwiseAND(F.lit((1 << width) - 1).cast("long"))
        keys.append(F.struct(F.lit(n).alias("k"), key.alias("v")))
    cells_of = fps.select(fp, F.explode(F.array(*keys)).alias("key")).select("fp", "key.k", "key.v")
    size = cells_of.groupBy("k", "v").agg(F.count("*").alias("n")).where("n > 1")
    shared = cells_of.join(size, ["k", "v"]).withColumn("blocks", F.ceil(F.col("n") / BLOCK).cast("int"))
    own = F.pmod(F.xxhash64(F.lit(7), "fp"), F.col("blocks")).cast("int")
    tasks = shared.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    tasks = tasks.select("k", "v", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "fp")
    dealt = tasks.repartition("k", "v", "i", "j").sortWithinPartitions("k", "v", "i", "j", "own", "fp")

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def pairs(t: pa.Table) -> Iterator[pa.RecordBatch]:
            col = [t.column(c).to_numpy() for c in range(6)]
            new = np.ones(len(col[0]), bool)
            new[1:] = np.any([c[1:] != c[:-1] for c in col[:4]], axis=0)
            starts = np.flatnonzero(new)
            ends = np.r_[starts[1:], len(new)]
            f = col[5].astype(np.int64).view(np.uint64)
            src, dst = [], []
            # small buckets, all at once: each fingerprint with the one d places on, while that is in its bucket
            size = ends - starts
            end = np.repeat(np.where(size <= SMALL, ends, starts), size)
            i, d = np.arange(len(f)), 0
            while len(i):
                d += 1
                i = i[i + d < end[i]]
                x = f[i] ^ f[i + d]
                near = np.bitwise_count(x) <= tau
                near[near] = passes_ring(x[near], tau, segments)
                src.append(f[i[near]])
                dst.append(f[i[near] + d])
            for s, e in zip(starts.tolist(), ends.tolist()):
                if e - s > SMALL:
                    first = col[4][s:e] == col[2][s]
                    a = f[s:e][first]
                    if col[2][s] == col[3][s]:
                        u, v = _forest(a, a, tau, segments)
                    else:
                        u, v = _forest(a, f[s:e][~first], tau, segments)
                    src.append(u)
                    dst.append(v)
            if src:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(src).view(np.int64)), pa.array(np.concatenate(dst).view(np.int64))], names=["src", "dst"])

        held: pa.Table | None = None
        for b in batches:  # a bucket's rows may come in several batches: hold back the last one
            t = pa.Table.from_batches([b])
            held = t if held is None else pa.concat_tables([held, t])
            if held.num_rows < 150_000:
                continue
            keyed = [held.column(c).to_numpy() for c in range(4)]
            last = np.all([c == c[-1] for c in keyed], axis=0)
            cut = int(np.argmax(last))
            if cut:
                yield from pairs(held.slice(0, cut))
                held = held.slice(cut)
        if held is not None and held.num_rows:
            yield from pairs(held)

    return dealt.mapInArrow(run, "src long, dst long")


def groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, tau: int = 3) -> DataFrame:
    """One row per document: (doc_id, fp, component_id), component_id the smallest doc_id reachable over links."""
    own = stash(fingerprints(docs, id_col, text_col, words), "simhash")
    first = own.groupBy("fp").agg(F.min("doc_id").alias("doc_id"))
    label = connected(links(first.select("fp"), tau))
    named = first.join(label.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "doc_id", F.coalesce("root", "fp").alias("root"))
    named = stash(named, "simhash")
    low = named.groupBy("root").agg(F.min("doc_id").alias("component_id"))
    return own.join(named.join(low, "root").select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")


def shingle_set(text: str | None, words: int) -> np.ndarray:
    """Distinct 64-bit hashes of a text's word shingles, lower-cased like the fingerprint."""
    w = (text or "").encode("utf-8", "surrogatepass").lower().split()
    k = min(words, len(w)) or 1
    joined = b" ".join(w)
    size = np.fromiter(map(len, w), np.int64, len(w))
    ends = np.cumsum(size + 1) - 1
    starts = (ends - size)[: max(0, len(w) - k + 1)].tolist() or [0]
    ends = ends[k - 1 :].tolist() or [0]
    digest = xxhash.xxh64_intdigest
    return np.unique(np.array([digest(joined[s:e]) for s, e in zip(starts, ends)], np.uint64)).astype(np.int64)


def width(n: int) -> int:
    """Bits of the bitmap that a row of a text with n shingles carries."""
    return MARK if n <= 2 * MARK else WIDE


def parity(shingles: np.ndarray) -> bytes:
    """A bitmap of width() bits or about one bit a shingle, if more, each bit the parity of the shingles that fall on it.

    Two bitmaps differ in no more bits than the two sets differ in shingles. Sizes are powers of two: a larger bitmap folds to a smaller one.
    """
    size = max(width(len(shingles)), 1 << (len(shingles) - 1).bit_length())
    odd = np.bincount((shingles & (size - 1)).astype(np.int64), minlength=size) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").tobytes()


def folded(bits: bytes, to: int) -> bytes:
    """The bitmap folded to that many bits, if it has more: rows of one width can be compared many at a time."""
    return np.bitwise_xor.reduce(np.frombuffer(bits, np.uint64).reshape(-1, min(to, 8 * len(bits)) // 64), axis=0).tobytes()


def may_reach(x: bytes, y: bytes, n: int, m: int, similarity: float) -> bool:
    """False only where sets of n and m shingles with these bitmaps cannot have so high a Jaccard similarity."""
    a, b = (x, y) if len(x) >= len(y) else (y, x)
    u, v, bits = int.from_bytes(a, "little"), int.from_bytes(b, "little"), len(a) * 8
    while bits > len(b) * 8:
        bits //= 2
        u = (u >> bits) ^ (u & ((1 << bits) - 1))
    return (u ^ v).bit_count() <= (1 - similarity) / (1 + similarity) * (n + m) + 1e-6


def text_key(text: Column) -> Column:
    """64 bits of a text's md5 as a signed long; null counts as empty."""
    h = F.md5(F.coalesce(text, F.lit("")).cast("binary"))
    high, low = (F.conv(F.substring(h, at, 8), 16, 10).cast("long") for at in (1, 9))
    return F.shiftleft(high, 32).bitwiseOR(low)


def common_shingles(texts: DataFrame, words: int) -> tuple[np.ndarray, np.ndarray]:
    """(shingles, ranks): those that several texts of a sample hold, sorted by hash. They only set an order, so a poor sample costs time, not links."""

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for t in b.column(0).to_pylist():
                yield pa.RecordBatch.from_arrays([pa.array(shingle_set(t, words))], names=["h"])

    step = max(1, -(-texts.count() // SAMPLE))
    some = texts.where(F.pmod(F.xxhash64(F.lit(3), "doc_id", "node"), F.lit(step)) == 0).select("text")
    seen = some.mapInArrow(run, "h long").groupBy("h").agg(F.count("*").alias("n")).where("n > 2").orderBy(F.desc("n"), "h").limit(RANKED).collect()
    h = np.array([r["h"] for r in seen], np.int64)
    order = np.argsort(h)
    release_driver(texts.sparkSession)
    return h[order], np.arange(len(h), 0, -1)[order]


_POSTING = "kind int, bucket long, doc_id long, node long, n int, bits binary, h long, pos int, packed binary"


def _posting_batch(kind: int, **cols: pa.Array) -> pa.RecordBatch:
    """Rows of one kind: 0 a text, with its folded bitmap, 1 a shingle that several texts share, 2 packed shingles of a bucket."""
    size = len(next(iter(cols.values())))
    types = {"kind": pa.int32(), "bucket": pa.int64(), "doc_id": pa.int64(), "node": pa.int64(), "n": pa.int32(), "bits": pa.binary(), "h": pa.int64(), "pos": pa.int32(), "packed": pa.binary()}
    cols["kind"] = pa.array(np.full(size, kind, np.int32))
    return pa.RecordBatch.from_arrays([cols[c].cast(t) if c in cols else pa.nulls(size, t) for c, t in types.items()], names=list(types))


def postings(texts: DataFrame, words: int, similarity: float) -> tuple[DataFrame, DataFrame]:
    """(doc_id, node, n, bits, mark) of each text, and (h, node, n, pos) of the prefix shingles that texts of several nodes share.

    texts(doc_id, node, text). Shingles stand in one order for all texts,
    common ones last. A text with n shingles shares at least similarity * n
    of them with a similar one, so leaving out all but one of so many from
    the end still leaves a shared one. Most shingles stand in one text only:
    they travel packed, once, to a bucket that tells which are shared. What
    is shared within HELD shingles of one task sends the bucket one entry.
    """
    hot, rank = common_shingles(texts, words)
    total = texts.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = max(4, -(-total // (30 * BUCKET_ENTRIES)))  # about one prefix shingle in 30 bytes

    def prefix(s: np.ndarray) -> np.ndarray:
        late = np.zeros(len(s), np.int64)
        if len(hot):
            spot = np.minimum(np.searchsorted(hot, s), len(hot) - 1)
            late = np.where(hot[spot] == s, rank[spot], 0)
        return s[np.lexsort((s, late))][: len(s) - math.ceil(similarity * len(s) - 1e-9) + 1]

    def dealt(kept: dict[int, tuple[int, np.ndarray]]) -> Iterator[pa.RecordBatch]:
        size = np.array([len(x) for _, x in kept.values()])
        h = np.concatenate([x for _, x in kept.values()])
        node = np.repeat(np.fromiter(kept, np.int64, len(kept)), size)
        n = np.repeat(np.array([k for k, _ in kept.values()], np.int32), size)
        pos = (np.arange(len(h)) - np.repeat(np.cumsum(size) - size, size)).astype(np.int32)
        order = np.argsort(h, kind="stable")
        head = np.r_[True, h[order][1:] != h[order][:-1]]
        many = np.diff(np.r_[np.flatnonzero(head), len(h)]) > 1
        shared = np.zeros(len(h), bool)
        shared[order] = many[np.cumsum(head) - 1]
        to = ((h.view(np.uint64) >> np.uint64(17)) % np.uint64(buckets)).astype(np.int64)
        if shared.any():
            yield _posting_batch(1, **{c: pa.array(v[shared]) for c, v in (("bucket", to), ("h", h), ("node", node), ("n", n), ("pos", pos))})
        sent = np.ones(len(h), bool)
        sent[shared] = False
        sent[order[head]] = True
        at = np.flatnonzero(sent)
        at = at[np.argsort(to[at], kind="stable")]
        mark = np.where(shared, -1, pos).astype(np.int32)
        cut = np.flatnonzero(np.r_[True, to[at][1:] != to[at][:-1], True])
        rows = [at[i:j] for i, j in zip(cut[:-1], cut[1:])]
        packed = [h[r].astype("<i8").tobytes() + node[r].astype("<i8").tobytes() + n[r].astype("<i4").tobytes() + mark[r].astype("<i4").tobytes() for r in rows]
        yield _posting_batch(2, bucket=pa.array(to[[r[0] for r in rows]]), packed=pa.array(packed, pa.binary()))

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: dict[int, tuple[int, np.ndarray]] = {}
        held = 0
        for b in batches:
            sizes, maps = [], []
            for node, t in zip(b.column(1).to_pylist(), b.column(2)):
                s = shingle_set(t.as_py(), words)
                sizes.append(len(s))
                maps.append(parity(s))
                if node not in kept:
                    kept[node] = len(s), prefix(s)
                    held += len(kept[node][1])
                if held > HELD:
                    yield from dealt(kept)
                    kept, held = {}, 0
            node = b.column(1)
            bucket = (node.to_numpy().view(np.uint64) % np.uint64(buckets)).astype(np.int64)
            yield _posting_batch(0, bucket=pa.array(bucket), doc_id=b.column(0), node=node, n=pa.array(sizes, pa.int32()), bits=pa.array(maps, pa.binary()), packed=pa.array([folded(m, width(k)) for m, k in zip(maps, sizes)], pa.binary()))
        if kept:
            yield from dealt(kept)

    def meet(t: pa.Table) -> pa.Table:
        kind = t.column("kind").to_numpy()
        out = [t.filter(pa.array(kind < 2))]
        parts: list[list[np.ndarray]] = [[], [], [], []]
        for v in t.filter(pa.array(kind == 2)).column("packed"):
            raw = v.as_buffer()
            k = raw.size // 24
            for p, (dtype, at) in zip(parts, (("<i8", 0), ("<i8", 8 * k), ("<i4", 16 * k), ("<i4", 20 * k))):
                p.append(np.frombuffer(raw, dtype, k, at))
        if parts[0]:
            h, node, n, pos = (np.concatenate(p) for p in parts)
            order = np.lexsort((node, h))
            hs, ns, told = h[order], node[order], pos[order] < 0
            heads = np.flatnonzero(np.r_[True, hs[1:] != hs[:-1]])
            last = np.r_[heads[1:], len(hs)] - 1
            several = (ns[heads] != ns[last]) | np.logical_or.reduceat(told, heads)
            keep = np.repeat(several, last - heads + 1) & ~told
            keep &= np.r_[True, (hs[1:] != hs[:-1]) | (ns[1:] != ns[:-1]) | told[:-1]]
            r = order[keep]
            out.append(pa.Table.from_batches([_posting_batch(1, h=pa.array(h[r]), node=pa.array(node[r]), n=pa.array(n[r]), pos=pa.array(pos[r]))]))
        release()
        return pa.concat_tables([x.select(out[0].column_names).cast(out[0].schema) for x in out])

    sent = texts.select("doc_id", "node", "text").mapInArrow(run, _POSTING)
    met = stash(sent.groupBy("bucket").applyInArrow(meet, _POSTING), "postings")
    return met.where("kind = 0").select("doc_id", "node", "n", "bits", F.col("packed").alias("mark")), met.where("kind = 1").select("h", "node", "n", "pos")


def spokes(rows: DataFrame, similarity: float) -> DataFrame:
    """Pairs (src, dst) of each row's node with its bucket's head, rows(node, n, low); one row a bucket member at most."""
    fit = F.least("n", "low.n") >= similarity * F.greatest("n", "low.n") - 1e-9
    return rows.where((F.col("node") != F.col("low.node")) & fit).select(F.least("node", "low.node").alias("src"), F.greatest("node", "low.node").alias("dst")).distinct()


def undecided(rows: DataFrame) -> DataFrame:
    """The rows of buckets h that hold nodes of several components."""
    size = rows.groupBy("h").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).where("low < high").select("h")
    return rows.join(size, "h")


def crossed(rows: DataFrame, similarity: float) -> DataFrame:
    """Pairs (src, dst) of rows(h, comp, node, n, pos, mark) that share h, are of different comp and may reach the similarity; a pair may come once for each h.

    Buckets of over BLOCK rows are compared in pairs of blocks in separate tasks, so none is cut short.
    """
    size = rows.groupBy("h").agg(F.count("*").alias("m"), F.min("comp").alias("low"), F.max("comp").alias("high")).where("low < high").select("h", "m")
    shared = rows.join(size, "h").withColumn("blocks", F.ceil(F.col("m") / BLOCK).cast("int"))
    dealt = shared.withColumn("own", F.pmod(F.xxhash64(F.lit(7), "node"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("h", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "comp", "node", "n", "pos", "mark")
    dealt = dealt.repartition("h", "i", "j").sortWithinPartitions("h", "i", "j", "own")

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def pairs(t: pa.Table) -> Iterator[pa.RecordBatch]:
            h, i, j, own, comp, node, n, pos = (t.column(c).to_numpy() for c in range(8))
            left = n - pos  # with h the first shared shingle, no more than so many are shared
            marks = t.column(8).to_pylist()
            mark = np.frombuffer(b"".join([folded(m, MARK) if len(m) * 8 > MARK else m for m in marks]), np.uint64).reshape(-1, MARK // 64)
            big_rows = [k for k, m in enumerate(marks) if len(m) * 8 == WIDE]
            wide = np.frombuffer(b"".join([marks[k] for k in big_rows]), np.uint64).reshape(-1, WIDE // 64)
            spot = np.full(len(marks), -1)
            spot[big_rows] = np.arange(len(big_rows))

            def near(of: np.ndarray, a: np.ndarray, b: np.ndarray, need: np.ndarray) -> np.ndarray:
                ok = [np.bitwise_count(of[a[k : k + 8192]] ^ of[b[k : k + 8192]]).sum(axis=1, dtype=np.int64) for k in range(0, len(a), 8192)]
                return np.concatenate([*ok, np.zeros(0, np.int64)]) <= (1 - similarity) / similarity * need + 1e-6

            def told(a: np.ndarray, b: np.ndarray) -> Iterator[pa.RecordBatch]:
                big, small = np.maximum(n[a], n[b]), np.minimum(n[a], n[b])
                need = similarity / (1 + similarity) * (big.astype(np.int64) + small)
                ok = (comp[a] != comp[b]) & (small >= similarity * big - 1e-9) & (np.minimum(left[a], left[b]) >= need - 1e-6)
                a, b, need = a[ok], b[ok], need[ok]
                ok = near(mark, a, b, need)
                both = np.flatnonzero(ok & (spot[a] >= 0) & (spot[b] >= 0))
                ok[both] = near(wide, spot[a[both]], spot[b[both]], need[both])
                a, b = a[ok], b[ok]
                if len(a):
                    x, y = node[a], node[b]
                    yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y))], names=["src", "dst"])

            starts = np.flatnonzero(np.r_[True, (h[1:] != h[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1])])
            ends = np.r_[starts[1:], len(h)]
            # small buckets, all at once: each row with the one d places on, while that is in its bucket
            end = np.repeat(np.where(ends - starts <= SMALL, ends, starts), ends - starts)
            at, d = np.arange(len(h)), 0
            while len(at):
                d += 1
                at = at[at + d < end[at]]
                if len(at):
                    yield from told(at, at + d)
            for s, e in zip(starts.tolist(), ends.tolist()):
                if e - s <= SMALL:
                    continue
                a = np.arange(s, e)
                if i[s] == j[s]:
                    for k in range(1, e - s):
                        yield from told(a[:-k], a[k:])
                else:
                    first = own[s:e] == i[s]
                    x, y = a[first], a[~first]
                    for k in x.tolist():
                        yield from told(np.full(len(y), k), y)

        held: pa.Table | None = None
        for b in batches:  # a bucket's rows may come in several batches: hold back the last one
            t = pa.Table.from_batches([b])
            held = t if held is None else pa.concat_tables([held, t])
            if held.num_rows < 150_000:
                continue
            keyed = [held.column(c).to_numpy() for c in range(3)]
            cut = int(np.argmax(np.all([c == c[-1] for c in keyed], axis=0)))
            if cut:
                yield from pairs(held.slice(0, cut))
                held = held.slice(cut)
        if held is not None and held.num_rows:
            yield from pairs(held)

    return dealt.mapInArrow(run, "src long, dst long")


def plausible(pairs: DataFrame, maps: DataFrame, similarity: float) -> DataFrame:
    """The pairs (src, dst) whose parity bitmaps allow the similarity; maps(node, n, bits). It drops no similar pair, and whole shingle sets move for the others only."""

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x, y, n, m = (b.column(c).to_pylist() for c in range(2, 6))
            ok = pa.array([may_reach(*r, similarity) for r in zip(x, y, n, m)], pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column(0).filter(ok), b.column(1).filter(ok)], names=["src", "dst"])

    side = lambda end, a, b: maps.select(F.col("node").alias(end), F.col("bits").alias(a), F.col("n").alias(b))
    both = pairs.join(side("src", "x", "nx"), "src").join(side("dst", "y", "ny"), "dst")
    return both.select("src", "dst", "x", "y", "nx", "ny").mapInArrow(run, "src long, dst long")


def verified(pairs: DataFrame, reps: DataFrame, texts: DataFrame, words: int, similarity: float) -> DataFrame:
    """The pairs (src, dst) of nodes whose texts' word shingles have a Jaccard similarity of at least `similarity`.

    Only texts that stand at a pair are read; they move by id, one pair's two shingle sets meet in one row.
    """
    pairs = stash(pairs, "pairs")
    ends = pairs.select(F.col("src").alias("node")).unionAll(pairs.select("dst")).distinct().join(reps, "node")
    ends = stash(ends, "ends")  # its size is known then, so texts do not move where it is small

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sets = [shingle_set(t, words).astype("<i8").tobytes() for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sets, pa.binary())], names=["node", "shingles"])

    read = texts.join(ends, ["doc_id", "node"], "left_semi").select("node", "text")
    sets = stash(read.mapInArrow(run, "node long, shingles binary"), "shingles").dropDuplicates(["node"])
    both = pairs.join(sets.select(F.col("node").alias("src"), F.col("shingles").alias("x")), "src").join(sets.select(F.col("node").alias("dst"), F.col("shingles").alias("y")), "dst")

    @tidy
    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ok = []
            for x, y in zip(b.column(2).to_pylist(), b.column(3).to_pylist()):
                u, v = np.frombuffer(x, "<i8"), np.frombuffer(y, "<i8")
                common = len(np.intersect1d(u, v, assume_unique=True))
                ok.append(common >= similarity * (len(u) + len(v) - common) - 1e-9)
            m = pa.array(ok, pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column(0).filter(m), b.column(1).filter(m)], names=["src", "dst"])

    return both.select("src", "dst", "x", "y").mapInArrow(check, "src long, dst long")


def alike(texts: DataFrame, tau: int = 3, words: int = 3) -> DataFrame:
    """Pairs (src, dst) of nodes whose fingerprints are within tau bits; texts(node, text).

    Links of fingerprints join the smallest node of each, and every other
    node of a fingerprint meets that one.
    """
    own = stash(fingerprints(texts, "node", "text", words).distinct().withColumnRenamed("doc_id", "node"), "simhash")
    first = own.groupBy("fp").agg(F.min("node").alias("head"))
    within = own.join(first, "fp").where("node <> head").select(F.col("head").alias("a"), F.col("node").alias("b"))
    end = lambda fp, head: first.select(F.col("fp").alias(fp), F.col("head").alias(head))
    across = links(first.select("fp"), tau).join(end("src", "a"), "src").join(end("dst", "b"), "dst").select("a", "b")
    return within.unionAll(across).select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst")).distinct()


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 5, similarity: float = 0.8) -> DataFrame:
    """The rows of docs that stay: one for each group, that of the smallest id; all columns pass through.

    Groups are the components of all pairs of texts whose `words`-word
    shingles reach `similarity`. Texts with close fingerprints are compared
    first, the search behind that is exact: similar texts share a shingle of
    their prefixes. Each text is compared with one of each bucket it is in,
    then with all of its buckets that are not in its group already. Equal texts are one node. Rows with a null id stay; rows of one
    id with different texts are told apart.
    """
    keyed = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_key(F.col(text_col)).alias("node"), F.col(text_col).alias("text")).where("doc_id is not null")
    spark = docs.sparkSession
    near = stash(alike(keyed), "near")
    release_driver(spark)
    texts, rows = postings(keyed, words, similarity)
    release_driver(spark)
    first = stash(texts.groupBy("node").agg(F.min("doc_id").alias("doc_id")), "first")
    maps = texts.select("node", "n", "bits", "mark")
    if texts.count() != first.count():  # equal texts stand in several rows
        maps, rows = maps.dropDuplicates(["node"]), rows.dropDuplicates(["h", "node"])
    told = F.struct(F.xxhash64("h", "node").alias("o"), "node", "n")  # another head in each bucket: a text meets many heads
    heads = rows.groupBy("h").agg(F.min(told).alias("low"), F.count("*").alias("m")).where("m > 1")
    shared = stash(rows.join(stash(heads, "heads"), "h"), "shared")
    star = stash(spokes(shared, similarity).unionAll(near).distinct(), "star")
    links = stash(verified(plausible(star, maps, similarity), first, keyed, words, similarity), "links")
    release_driver(spark)
    label = stash(connected(links).withColumnRenamed("root", "comp"), "label")
    release_driver(spark)
    open_ = shared.where("m > 2").join(label, "node", "left").select("h", F.coalesce("comp", "node").alias("comp"), "node", "n", "pos")
    open_ = stash(undecided(open_), "open")
    drop_stash(shared)
    release_driver(spark)
    rest = stash(crossed(open_.join(maps.select("node", "mark"), "node"), similarity).distinct().join(star, ["src", "dst"], "left_anti"), "rest")
    drop_stash(open_)
    more = stash(verified(plausible(rest, maps, similarity), first, keyed, words, similarity), "links")
    release_driver(spark)
    if more.limit(1).count():
        label = connected(links.unionAll(more)).withColumnRenamed("root", "comp")
    named = first.join(label, "node", "left").select("node", "doc_id", F.coalesce("comp", "node").alias("comp"))
    stays = named.groupBy("comp").agg(F.min(F.struct("doc_id", "node")).alias("s")).select(F.col("s.doc_id").alias(id_col), F.col("s.node").alias("__text_key"))
    kept = docs.withColumn("__text_key", text_key(F.col(text_col))).join(stays, [id_col, "__text_key"], "left_semi")
    if texts.groupBy("doc_id", "node").count().where("count > 1").limit(1).count():  # whole rows move only where rows repeat
        kept = kept.dropDuplicates([id_col, "__text_key"])
    return kept.drop("__text_key").unionByName(docs.where(F.col(id_col).isNull()))
