"""Sequence packing by cutting-stock column generation.

Documents become token ids. A document longer than a sequence is cut: its
full parts are sequences of their own, the rest is a piece to pack. The
histogram of piece sizes (in units of `grain` tokens, so at most
capacity / grain rows reach the driver) is the demand of a cutting-stock
problem: a restricted linear program over patterns, new patterns priced by an
unbounded-knapsack dynamic program, until none has negative reduced cost.
Patterns are used floor(x) times; what is left over is placed first-fit
decreasing on the histogram. Pieces are ranked inside their size (in salted
sub-groups, with offsets from a small table of counts) and the ranks are laid
along the patterns.

Edge cases: null text counts as empty (one piece: the end id alone); repeated
rows are packed once each; an empty table gives no rows; only the id and text
columns are read.
"""

from __future__ import annotations

import os
import re
import unicodedata
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from ..plans.storage import stash
from .memory import release_driver, tidy

CAPACITY = 2048
GRAIN = 8
END_ID = 1
CACHE_WORDS = 200_000  # bound of one worker's word cache
BATCH_IDS = 1 << 20  # ids after which a batch of pieces is handed on
RANKED_ROWS = 50_000  # rows of one sub-group that is ranked in one task

_PLAIN = re.compile(r"[\t\n\r -~À-ÖØ-öø-ÿ]*")
_PIECES = re.compile(r"'(?:s|t|re|ve|m|ll|d)|[a-zß-öø-ÿ]+|[0-9]|[!-/:-@\[-`{-~]+")


class WordCache:
    """Token ids as little-endian bytes, by cached words.

    Texts of ASCII and Latin letters are cut as the tokenizer's own splitter
    cuts them; any other text goes to the tokenizer whole. Unseen words are
    encoded together, one call a batch.
    """

    def __init__(self, path: str | None = None, spec: str | None = None) -> None:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_str(spec) if spec else Tokenizer.from_file(path)
        self.ids: dict[str, bytes] = {}

    def _learn(self, words: list[str]) -> None:
        if len(self.ids) + len(words) > CACHE_WORDS:
            self.ids.clear()
        for at in range(0, len(words), 4096):
            part = words[at : at + 4096]
            e = self.tok.encode(" ".join(part), add_special_tokens=False)
            of = np.array(e.word_ids)
            raw = np.array(e.ids, "<u4").tobytes()
            cut = [*np.flatnonzero(np.r_[True, of[1:] != of[:-1]]).tolist(), len(of)]
            if len(cut) != len(part) + 1:  # never seen; then word by word
                self.ids.update((w, np.array(self.tok.encode(w, add_special_tokens=False).ids, "<u4").tobytes()) for w in part)
            else:
                self.ids.update((w, raw[4 * a : 4 * b]) for w, a, b in zip(part, cut, cut[1:]))

    def encode(self, text: str) -> bytes:
        if not _PLAIN.fullmatch(text) or "<|" in text or not unicodedata.is_normalized("NFC", text):
            return np.array(self.tok.encode(text, add_special_tokens=False).ids, "<u4").tobytes()
        words = _PIECES.findall(text.lower())
        try:
            return b"".join(map(self.ids.__getitem__, words))
        except KeyError:
            self._learn(list({w for w in words if w not in self.ids}))
            got = self.ids
            if any(w not in got for w in words):  # the cache was emptied on the way
                self._learn(list(set(words)))
            return b"".join(map(self.ids.__getitem__, words))


def tokenized_pieces(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, payload: str = "ids", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: (doc_id, start, length, doc_tokens, and ids or their CRC-32)."""
    kind = {"ids": "ids array<int>", "crc32": "ids_crc32 long"}[payload]
    # the tokenizer's file is small and fixed: ship its content, so executors need no path
    spec = open(tokenizer_path, encoding="utf-8").read()  # noqa: SIM115
    share = docs.sparkSession.sparkContext.broadcast(spec)

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = _cache_of(share)
        types = [pa.int64()] * 4 + [pa.int64() if payload == "crc32" else pa.list_(pa.int32())]

        def batch(out: list[list]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(o, t) for o, t in zip(out, types)], names=["doc_id", "start", "length", "doc_tokens", kind.split()[0]])

        out: list[list] = [[], [], [], [], []]
        held = 0
        for b in batches:
            keys, texts = b.column(0).cast(pa.int64()).to_pylist(), b.column(1)
            for key, text in zip(keys, texts):
                raw = cache.encode(text.as_py() or "") + END_ID.to_bytes(4, "little")
                n = len(raw) // 4
                for start in range(0, n, capacity):
                    part = raw[4 * start : 4 * (start + capacity)]
                    for o, v in zip(out, (key, start, len(part) // 4, n, zlib.crc32(part) if payload == "crc32" else np.frombuffer(part, "<i4"))):
                        o.append(v)
                held += n
                if held >= BATCH_IDS:
                    yield batch(out)
                    out, held = [[], [], [], [], []], 0
        if out[0]:
            yield batch(out)

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, f"doc_id long, start long, length long, doc_tokens long, {kind}")


_caches: dict[int, WordCache] = {}


def _cache_of(share) -> WordCache:  # noqa: ANN001
    """One cache for each Python worker, kept between tasks."""
    spec = share.value
    key = zlib.crc32(spec.encode())
    if key not in _caches:
        _caches[key] = WordCache(spec=spec)
    return _caches[key]


# ---------------------------------------------------------------- the linear program


def knapsack(value: np.ndarray, room: int) -> tuple[np.ndarray, np.ndarray]:
    """Unbounded knapsack over sizes 1..len(value): the best value for each room, and the size placed last (0: none)."""
    best, last = np.zeros(room + 1), np.zeros(room + 1, np.int64)
    for c in range(1, room + 1):
        m = min(c, len(value))
        got = value[:m] + best[c - m : c][::-1]
        i = int(got.argmax())
        if got[i] > best[c - 1] + 1e-12:
            best[c], last[c] = got[i], i + 1
        else:
            best[c] = best[c - 1]
    return best, last


def _pattern(last: np.ndarray, room: int, n: int, first: int) -> np.ndarray:
    """The pattern that places size first + 1 and fills the rest as the knapsack table says."""
    p = np.zeros(n, np.int64)
    p[first] = 1
    room -= first + 1
    while room > 0:
        p[last[room] - 1] += last[room] > 0
        room -= max(1, last[room])
    return p


def _inverse(a: np.ndarray) -> np.ndarray:
    """Gauss-Jordan with row exchange: a few hundred rank-one steps (threaded LAPACK can hang in a driver that has forked)."""
    n = len(a)
    w = np.hstack([a, np.eye(n)])
    for c in range(n):
        r = c + int(np.argmax(np.abs(w[c:, c])))
        w[[c, r]] = w[[r, c]]
        w[c] /= w[c, c]
        f = w[:, c].copy()
        f[c] = 0
        w -= np.outer(f, w[c])
    return w[:, n:]


def patterns_for(demand: np.ndarray, room: int, max_rounds: int = 200, gap: float = 1e-3) -> tuple[np.ndarray, np.ndarray]:
    """Column generation. demand[i]: pieces of size i + 1. Returns the basic patterns (one a row) and how often each is used.

    Each round prices by one knapsack table, from which the best pattern
    through every size joins a pool; simplex pivots then run over the pool.
    Demands are raised by up to 2 % of fixed noise, else ties stall the
    pivots. Ends when the dual bound is within `gap`.
    """
    sizes = np.flatnonzero(demand > 0)
    m = len(sizes)
    if not m:
        return np.zeros((0, len(demand)), np.int64), np.zeros(0)
    rng = np.random.default_rng(3)
    b = demand[sizes].astype(float)
    b = b * (1 + 0.02 * rng.random(m)) + 1e-3 * b.mean() * rng.random(m)
    fit = room // (sizes + 1)
    basis, inv = np.diag(fit).astype(float), np.diag(1.0 / fit)  # column j: as many pieces of size j as fit
    x = inv @ b
    pool, seen, bound, pivots = np.zeros((0, m)), set(), 0.0, 0
    for _ in range(max_rounds):
        value = np.zeros(len(demand))
        value[sizes] = np.maximum(inv.sum(axis=0), 0)  # every pattern costs one sequence
        best, last = knapsack(value, room)
        bound = max(bound, float(value[sizes] @ b) / max(best[room], 1.0))
        if best[room] <= 1 + 1e-9 or x.sum() <= bound * (1 + gap):
            break
        fresh = []
        for i in sizes.tolist():
            if value[i] + best[room - i - 1] > 1 + 1e-7:
                p = _pattern(last, room, len(demand), i)[sizes]
                if p.tobytes() not in seen:
                    seen.add(p.tobytes())
                    fresh.append(p.astype(float))
        pool = np.vstack([pool, *fresh])
        for _ in range(3 * m):
            gain = pool @ inv.sum(axis=0)
            j = int(gain.argmax()) if len(gain) else -1
            if j < 0 or gain[j] <= 1 + 1e-7:
                break
            step = inv @ pool[j]
            can = step > 1e-9
            ratio = np.where(can, x / np.where(can, step, 1), np.inf)
            out = int(np.argmin(ratio))
            t = max(float(ratio[out]), 0.0)
            x = np.maximum(x - t * step, 0)
            x[out] = t
            basis[:, out] = pool[j]
            row = inv[out] / step[out]
            inv = inv - np.outer(step, row)
            inv[out] = row
            pivots += 1
            if pivots % 300 == 0:  # afresh, against rounding errors
                inv = _inverse(basis)
                x = np.maximum(inv @ b, 0)
        if len(pool) > 6000:
            pool = pool[np.argsort(-(pool @ inv.sum(axis=0)), kind="stable")[:3000]]
    found = np.zeros((m, len(demand)), np.int64)
    found[:, sizes] = np.rint(basis.T).astype(np.int64)
    return found, x


def plan(demand: np.ndarray, room: int) -> list[tuple[np.ndarray, int]]:
    """Whole patterns that hold every piece exactly once: (pieces by size, times used)."""
    found, x = patterns_for(demand, room)
    left = demand.astype(np.int64).copy()
    used: list[tuple[np.ndarray, int]] = []
    for p, times in sorted(zip(found, x), key=lambda v: (-v[1], v[0].tolist())):
        k = int(times + 1e-6)
        if p.any():
            k = min(k, int((left[p > 0] // p[p > 0]).min()))
        if k > 0 and p.any():
            used.append((p, k))
            left -= k * p
    while left.any():  # the rest is small: as many sizes as the program has rows, each a few pieces
        p, space = np.zeros_like(left), room
        for size in range(min(room, len(left)), 0, -1):
            k = min(int(left[size - 1]), space // size)
            if k:
                p[size - 1] = k
                space -= k * size
        k = int((left[p > 0] // p[p > 0]).min())
        used.append((p, k))
        left -= k * p
    return used


# ---------------------------------------------------------------- ranks and places


def pack(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, grain: int = GRAIN, payload: str = "ids", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces with their place: adds (sequence_id, offset) to the columns of tokenized_pieces()."""
    pieces = stash(tokenized_pieces(docs, tokenizer_path, capacity, payload, id_col, text_col), "pieces")
    spark = docs.sparkSession
    release_driver(spark)
    size = F.ceil(F.col("length") / F.lit(grain)).cast("int")
    total = pieces.count()
    salts = max(1, -(-total // RANKED_ROWS))
    salted = pieces.withColumn("size", size).withColumn("salt", F.pmod(F.xxhash64("doc_id", "start"), F.lit(salts)).cast("int"))
    counts = salted.groupBy("size", "salt").agg(F.count("*").alias("n"))
    demand = np.zeros(-(-capacity // grain), np.int64)
    for r in counts.groupBy("size").agg(F.sum("n").alias("n")).collect():  # at most capacity / grain rows
        demand[r["size"] - 1] = r["n"]
    room = capacity // grain
    laid, at, taken = [], 0, np.zeros(len(demand), np.int64)
    for p, times in plan(demand, room):
        slot = 0
        for i in np.flatnonzero(p).tolist():
            each = int(p[i])
            laid.append((i + 1, int(taken[i]), int(taken[i]) + each * times, at, each, slot))
            taken[i] += each * times
            slot += each
        at += times
    # the pattern table has a proven bound: the program has capacity / grain rows, whatever the data
    places = spark.createDataFrame(laid, "size int, lo long, hi long, first_sequence long, each int, slot int")
    before = Window.partitionBy("size").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0))).drop("n")
    inside = Window.partitionBy("size", "salt").orderBy("doc_id", "start", "doc_tokens", pieces.columns[4])
    ranked = salted.withColumn("rn", F.row_number().over(inside)).join(offsets, ["size", "salt"])
    ranked = ranked.withColumn("rank", F.col("before") + F.col("rn") - 1).drop("rn", "before", "salt")
    joined = ranked.join(F.broadcast(places), "size").where((F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi")))
    k = F.col("rank") - F.col("lo")
    placed = joined.withColumn("sequence_id", F.col("first_sequence") + (k / F.col("each")).cast("long")).withColumn("slot", F.col("slot") + k % F.col("each"))
    run = Window.partitionBy("sequence_id").orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)  # at most capacity pieces
    placed = placed.withColumn("offset", F.coalesce(F.sum("length").over(run), F.lit(0)))
    return placed.select(*pieces.columns, "sequence_id", "offset")


def sequences(packed: DataFrame, capacity: int = CAPACITY, pad_id: int = 0) -> DataFrame:
    """(sequence_id, ids, used): padded rows for training; a length that is a power of two is left as it is."""
    held = packed.groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("parts"))
    ids = F.flatten(F.transform("parts", lambda p: p["ids"]))
    out = held.select("sequence_id", ids.alias("ids")).withColumn("used", F.size("ids"))
    whole = F.bit_count("used") == 1
    return out.withColumn("ids", F.when(whole, F.col("ids")).otherwise(F.concat("ids", F.array_repeat(F.lit(pad_id), F.greatest(F.lit(capacity) - F.col("used"), F.lit(0))))))


def public_tokenizer(name: str = "word_bpe_49k.json") -> str:
    """Where the public vocabulary file lies on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


Encoder = Callable[[str], bytes]
