"""Language identification by error-correcting output codes.

Each language has a codeword of bits. One binary linear classifier per bit
reads hashed character n-grams. Decoding sums the logistic losses of each
codeword's bits and takes the nearest codeword; a small gap to the second
flags ambiguity.

Fitting uses a bounded sample of labelled rows (`sample_rows`, spread over the
languages by a hash of the id); prediction reads every whole text.

Edge cases: null text, or text without a letter: `und` with score 0; no
labelled rows at all: `und` for every row; one language: that language;
repeated rows: repeated results; only the named columns are read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F
from .memory import release_driver, tidy

SAMPLE_ROWS = 4000
BUCKETS = 4096
_LETTER = re.compile(r"[^\W\d_]")
_TABLE = bytes(c if 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
CHUNK = 1 << 20  # n-grams counted at a time, whatever the text's length


def features(text: str) -> np.ndarray:
    """Unit vector of the square roots of hashed counts of byte 1-, 2- and 3-grams in the lower-cased text."""
    raw = np.frombuffer(b" " + text.lower().encode("utf-8", "surrogatepass").translate(_TABLE) + b" ", np.uint8)
    counts = np.zeros(BUCKETS, np.int64)
    for at in range(0, len(raw), CHUNK):
        a = raw[at : at + CHUNK + 2].astype(np.uint32)
        one = a[:CHUNK]
        counts[:256] += np.bincount(one, minlength=256)
        two = a[: CHUNK + 1][:-1] * np.uint32(2654435761) + a[1 : CHUNK + 1] * np.uint32(40503)
        counts += np.bincount((two >> np.uint32(13)) % np.uint32(BUCKETS), minlength=BUCKETS)
        if len(a) > 2:
            three = a[:-2] * np.uint32(2654435761) + a[1:-1] * np.uint32(2246822519) + a[2:] * np.uint32(3266489917)
            three ^= three >> np.uint32(15)
            counts += np.bincount((three * np.uint32(668265263) >> np.uint32(11)) % np.uint32(BUCKETS), minlength=BUCKETS)
    counts[32] = 0
    v = np.sqrt(counts).astype(np.float32)
    return v / max(float(np.sqrt((v * v).sum())), 1e-9)


def codewords(n: int, seed: int = 11) -> np.ndarray:
    """n rows of -1 and 1. Up to 6 classes: every distinct split of the classes; more: the best of 200 random codes."""
    if n <= 1:
        return np.ones((n, 1), np.int8)
    if n <= 6:
        cols = [[1 if i == 0 or (k >> (i - 1)) & 1 else -1 for i in range(n)] for k in range(2 ** (n - 1) - 1)]
        return np.array(cols, np.int8).T
    rng = np.random.default_rng(seed)
    length = int(np.ceil(10 * np.log2(n)))
    best, gap = None, -1
    for _ in range(200):
        c = rng.choice(np.array([-1, 1], np.int8), (n, length))
        if (np.abs(c.sum(axis=0)) == n).any():
            continue
        d = length - (c.astype(int) @ c.T.astype(int) + length) // 2
        np.fill_diagonal(d, length)
        if d.min() > gap:
            best, gap = c, d.min()
    return best


def fit_bits(x: np.ndarray, y: np.ndarray, rounds: int = 150, l2: float = 1e-5) -> np.ndarray:
    """Logistic regressions for all bits at once: accelerated full gradients. Last row: intercepts."""
    w = np.zeros((x.shape[1] + 1, y.shape[1]), np.float32)
    back, rate = w.copy(), 4.0 / (float(np.einsum("ij,ij->", x, x, dtype=np.float64)) / len(x) + 1)  # from the curvature's bound
    for t in range(rounds):
        ahead = w + np.float32(t / (t + 3)) * (w - back)
        margin = np.clip((x @ ahead[:-1] + ahead[-1]) * y, -30, 30)
        slope = -y / (1 + np.exp(margin))
        grad = np.vstack([x.T @ slope, slope.sum(axis=0)]) / len(x) + l2 * ahead
        back, w = w, ahead - rate * grad
    return w


def learnable(id_col: Column, lang: Column) -> Column:
    """Rows that may be learned from."""
    return lang.isNotNull() & (F.crc32(id_col.cast("string").cast("binary")) % 4 != 2)


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", sample_rows: int = SAMPLE_ROWS) -> dict:
    """The model: languages, codewords, weights. At most sample_rows rows reach the driver, as hashed counts."""
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang")).where(learnable(F.col("doc_id"), F.col("lang")))
    have = sorted((r["lang"], r["n"]) for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect())
    langs = [k for k, _ in have]
    if not langs:
        return {"langs": [], "codes": codewords(0), "w": None}
    each = max(1, sample_rows // len(langs))
    share = F.create_map(*[v for k, n in have for v in (F.lit(k), F.lit(min(1.0, 1.3 * each / n + 20 / n)))])
    draw = F.xxhash64("doc_id", F.lit(17)) / F.lit(float(2**64)) + 0.5
    few = rows.where(draw < F.element_at(share, F.col("lang"))).where(F.col("text").isNotNull())
    nth = F.row_number().over(Window.partitionBy("lang").orderBy(F.xxhash64("doc_id", F.lit(17)), "doc_id"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            v = [features(t.as_py()).astype(np.float16).tobytes() for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(v, pa.binary())], names=["doc_id", "lang", "v"])

    kind = docs.schema[id_col].dataType.simpleString()
    counted = few.mapInArrow(count, f"doc_id {kind}, lang string, v binary").withColumn("nth", nth).where(F.col("nth") <= each)
    got = counted.select("lang", "v").toArrow().sort_by([("lang", "ascending"), ("v", "ascending")])
    if not got.num_rows:
        return {"langs": langs, "codes": codewords(len(langs)), "w": None}
    x = np.stack([np.frombuffer(v.as_buffer(), np.float16) for v in got.column("v")]).astype(np.float32)
    codes = codewords(len(langs))
    y = codes[[langs.index(k) for k in got.column("lang").to_pylist()]].astype(np.float32)
    del got
    release_driver(docs.sparkSession)
    return {"langs": langs, "codes": codes, "w": fit_bits(x, y) if len(langs) > 1 else None}


def decode(model: dict, x: np.ndarray) -> tuple[str, float, bool]:
    """Loss-weighted decoding: (language, score, ambiguous)."""
    langs, codes, w = model["langs"], model["codes"], model["w"]
    if not langs:
        return "und", 0.0, True
    if w is None:
        return langs[0], 1.0 / len(langs), len(langs) > 1
    margin = x @ w[:-1] + w[-1]
    loss = np.log1p(np.exp(-np.clip(codes * margin, -30, 30))).sum(axis=1)
    p = np.exp(loss.min() - loss)
    p /= p.sum()
    order = np.argsort(-p, kind="stable")
    return langs[order[0]], float(p[order[0]]), bool(len(p) > 1 and p[order[0]] - p[order[1]] < 0.2)


def predict(docs: DataFrame, model: dict, text_col: str = "text", prefix: str = "") -> DataFrame:
    """docs with lang_pred, score and ambiguous added (names with `prefix`); every column passes through."""
    at = docs.columns.index(text_col)
    names = [prefix + n for n in ("lang_pred", "score", "ambiguous")]
    # a fixed size: BUCKETS rows by the code's length
    share = docs.sparkSession.sparkContext.broadcast(model)

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = share.value
        for b in batches:
            out = []
            for v in b.column(at):
                t = v.as_py()
                out.append(decode(m, features(t)) if t is not None and _LETTER.search(t) else ("und", 0.0, True))
            add = [pa.array([o[i] for o in out], kind) for i, kind in enumerate((pa.string(), pa.float64(), pa.bool_()))]
            yield pa.RecordBatch.from_arrays([*b.columns, *add], names=[*b.schema.names, *names])

    schema = docs.schema
    for n, k in zip(names, ("string", "double", "boolean")):
        schema = type(schema)(list(schema.fields)).add(n, k)
    return docs.mapInArrow(run, schema)
