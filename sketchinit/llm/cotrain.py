"""Quality classification by co-training.

Two views of a document: its text (hashed byte 3-grams, case and marks kept)
and its page metadata (source, language, length, layout shares). Each view
has its own logistic regression. In every round each classifier labels the
unlabelled documents it is surest of for the other one. In the end both are
calibrated on labelled rows kept aside and combined by adding log-odds.

Fitting uses two bounded samples, parameters of fit() and score(): LABELLED
rows with a label and POOL rows that have none in the labels table, those of
the lowest hash of the id. Scoring reads every whole text.

Edge cases: null text counts as empty; null source or language is a value of
its own; without labels of both classes every score is the share of good
ones (0.5 without any); repeated rows give repeated results.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .langid import fit_bits

LABELLED, POOL, ROUNDS, SHARE = 3000, 3000, 5, 0.04
TEXT_BUCKETS, META_BUCKETS = 2048, 64
_MARKS = re.compile(r"[^\w\s]")
_DIGIT = re.compile(r"[0-9]")
_UPPER = re.compile(r"[A-ZÀ-ÖØ-Þ]")


def text_view(text: str | None) -> np.ndarray:
    raw = np.frombuffer((text or "").encode("utf-8", "surrogatepass"), np.uint8)
    counts = np.zeros(TEXT_BUCKETS, np.int64)
    for at in range(0, max(0, len(raw) - 2), 1 << 20):
        a = raw[at : at + (1 << 20) + 2].astype(np.uint32)
        h = a[:-2] * np.uint32(2654435761) + a[1:-1] * np.uint32(2246822519) + a[2:] * np.uint32(3266489917)
        h = (h ^ (h >> np.uint32(15))) * np.uint32(668265263)
        counts += np.bincount((h >> np.uint32(9)) % np.uint32(TEXT_BUCKETS), minlength=TEXT_BUCKETS)
    v = np.sqrt(counts).astype(np.float32)
    return v / max(float(np.sqrt((v * v).sum())), 1e-9)


def meta_view(text: str | None, source: str | None, lang: str | None) -> np.ndarray:
    t = text or ""
    n = max(1, len(t))
    lines = t.split("\n")
    words = t.split()
    v = np.zeros(META_BUCKETS, np.float32)
    v[:8] = (
        np.log1p(len(t)) / 12, np.log1p(len(lines)) / 8, min(1.0, len(words) / n * 6), len(_MARKS.findall(t)) / n * 4,
        len(_UPPER.findall(t)) / n * 2, len(set(words)) / max(1, len(words)), len(_DIGIT.findall(t)) / n * 4, len(set(lines)) / len(lines),
    )
    v[8 + zlib.crc32(f"s{source}".encode()) % 40] = 0.5
    v[48 + zlib.crc32(f"l{lang}".encode()) % 16] = 0.5
    return v


def _margin(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    return x @ w[:-1, 0] + w[-1, 0]


def _sigmoid(m: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(m, -30, 30)))


def calibrate(margin: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Slope and shift of a logistic curve through margins and labels (0 or 1), by bounded Newton steps with a unit ridge around slope 1 and shift 0."""
    a, b = 1.0, 0.0
    for _ in range(60):
        p = _sigmoid(a * margin + b)
        g = np.array([((p - y) * margin).sum() + (a - 1), (p - y).sum() + b])
        s = p * (1 - p)
        h = np.array([[(s * margin * margin).sum() + 1, (s * margin).sum()], [(s * margin).sum(), s.sum() + 1]])
        det = h[0, 0] * h[1, 1] - h[0, 1] * h[1, 0]
        a -= float(np.clip((h[1, 1] * g[0] - h[0, 1] * g[1]) / det, -0.3, 0.3))
        b -= float(np.clip((h[0, 0] * g[1] - h[1, 0] * g[0]) / det, -0.3, 0.3))
    return float(max(a, 0.05)), float(b)


def cotrain(views: list[np.ndarray], y: np.ndarray, pool: list[np.ndarray], rounds: int = ROUNDS, share: float = SHARE) -> dict:
    """views: the two views of labelled rows; pool: of unlabelled rows; y: 0 or 1."""
    prior = float(y.mean()) if len(y) else 0.5
    if len(set(y.tolist())) < 2:
        return {"prior": prior, "w": None}
    aside = np.arange(len(y)) % 4 == 3
    if len(set(y[aside].tolist())) < 2:
        aside = np.zeros(len(y), bool)
    taught = [[v[~aside], np.where(y[~aside] > 0, 1.0, -1.0)] for v in views]
    free = np.ones(len(pool[0]), bool)
    w = [fit_bits(x, t[:, None].astype(np.float32)) for x, t in taught]
    for _ in range(rounds):
        left = np.flatnonzero(free)
        if not len(left):
            break
        for mine, other in ((0, 1), (1, 0)):
            left = np.flatnonzero(free)
            k = max(1, int(share * len(pool[0]) / 2))
            p = _sigmoid(_margin(pool[mine][left], w[mine]))
            good = left[np.argsort(-p, kind="stable")[: int(k * 2 * prior) + 1]]
            bad = left[np.argsort(p, kind="stable")[: int(k * 2 * (1 - prior)) + 1]]
            good = good[_sigmoid(_margin(pool[mine][good], w[mine])) > 0.9]
            bad = bad[_sigmoid(_margin(pool[mine][bad], w[mine])) < 0.1]
            add = np.concatenate([good, bad])
            taught[other][0] = np.vstack([taught[other][0], pool[other][add]])
            taught[other][1] = np.concatenate([taught[other][1], np.ones(len(good)), -np.ones(len(bad))])
            free[add] = False
        w = [fit_bits(x, t[:, None].astype(np.float32)) for x, t in taught]
    held = aside if aside.any() else np.ones(len(y), bool)
    return {"prior": prior, "w": w, "curves": [calibrate(_margin(v[held], k), y[held]) for v, k in zip(views, w)]}


def combined(model: dict, x: list[np.ndarray]) -> tuple[float, float, float]:
    """(score, text score, metadata score) of one document."""
    if model["w"] is None:
        return (model["prior"],) * 3
    odds = [a * float(v @ w[:-1, 0] + w[-1, 0]) + b for v, w, (a, b) in zip(x, model["w"], model["curves"])]
    base = np.log(model["prior"] / (1 - model["prior"]))
    both = float(_sigmoid(np.array(sum(odds) - base)))
    return both, *(float(_sigmoid(np.array(o))) for o in odds)


def _least(ids: DataFrame, rows: int, *more: str) -> DataFrame:
    """At most `rows` rows, those whose ids hash lowest: the same ones whatever the plan is."""
    return ids.withColumn("_h", F.xxhash64("doc_id", F.lit(29))).orderBy("_h", "doc_id", *more).limit(rows).drop("_h")


def fit(docs: DataFrame, labels: DataFrame, target: str = "quality", id_col: str = "doc_id", text_col: str = "text", labelled: int = LABELLED, pool: int = POOL) -> dict:
    """The model, from at most `labelled` rows with a label and `pool` rows without: so many reach the driver, as features.

    Rows of one id with several labels count as the smaller one; rows
    without an id take no part in fitting.
    """
    known = labels.where(F.col(target).isNotNull()).groupBy(F.col(id_col).alias("doc_id")).agg(F.min(F.col(target).cast("int")).alias("y")).where("doc_id is not null")
    some = _least(known, labelled)
    base = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), "source", "lang")
    free = _least(base.select("doc_id").where("doc_id is not null").distinct().join(known, "doc_id", "left_anti"), pool)

    def seen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            t, s, g = (b.column(c).to_pylist() for c in ("text", "source", "lang"))
            xs = [pa.array([f.astype(np.float16).tobytes() for f in v], pa.binary()) for v in ([text_view(a) for a in t], [meta_view(*r) for r in zip(t, s, g)])]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("y"), *xs], names=["doc_id", "y", "a", "b"])

    kind = docs.schema[id_col].dataType.simpleString()

    def as_views(chosen: DataFrame, most: int) -> list:
        joined = base.join(F.broadcast(chosen), "doc_id").select(*base.columns, "y")  # at most `most` ids are broadcast
        got = joined.mapInArrow(seen, f"doc_id {kind}, y int, a binary, b binary").orderBy("doc_id", "a", "b").limit(most)
        return got.collect()

    rows, rest = as_views(some, labelled), as_views(free.withColumn("y", F.lit(-1)), pool)
    stack = lambda rs, c, n: np.stack([np.frombuffer(bytes(r[c]), np.float16) for r in rs]).astype(np.float32) if rs else np.zeros((0, n), np.float32)
    views, others = ([stack(rs, "a", TEXT_BUCKETS), stack(rs, "b", META_BUCKETS)] for rs in (rows, rest))
    return cotrain(views, np.array([r["y"] for r in rows]), others)


def score(docs: DataFrame, labels: DataFrame, target: str = "quality", id_col: str = "doc_id", text_col: str = "text", keep_from: float = 0.5, labelled: int = LABELLED, pool: int = POOL) -> DataFrame:
    """(doc_id, score, text_score, meta_score, keep) for every row of docs."""
    share = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, target, id_col, text_col, labelled, pool))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = share.value
        for b in batches:
            got = [combined(m, [text_view(t), meta_view(t, s, g)]) for t, s, g in zip(*(b.column(c).to_pylist() for c in ("text", "source", "lang")))]
            cols = [pa.array([r[i] for r in got], pa.float64()) for i in range(3)]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *cols, pa.array([r[0] >= keep_from for r in got], pa.bool_())], names=["doc_id", "score", "text_score", "meta_score", "keep"])

    kind = docs.schema[id_col].dataType.simpleString()
    base = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), "source", "lang")
    return base.mapInArrow(run, f"doc_id {kind}, score double, text_score double, meta_score double, keep boolean")
