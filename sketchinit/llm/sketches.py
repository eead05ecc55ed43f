"""Threshold-scaled document sketches, in DataFrame functions only.

A sketch keeps every word-shingle hash that lies below a fixed fraction of
the hash range. So the sketch of a union is the union of the sketches, and
the share of a small document's hashes that a large one holds estimates
containment without bias, however unequal the two are. A document none of
whose hashes lies below the threshold keeps its smallest hash, marked by
being above the threshold, so that it still can be compared; merge() drops
such marks when real entries exist.

Edge cases: null text counts as empty; fewer words than a shingle: the whole
sequence is one shingle; an empty text has the shingle of no words; equal
texts have equal sketches; repeated rows give repeated rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from ..plans.storage import stash

WORDS = 5
FRACTION_BITS = 3  # one hash in 2 ** FRACTION_BITS is kept
IDS_PER_RANGE = 4_000
KNOTS = 8_192  # quantiles of the ids that the plan holds
MAX_RANGES = 500_000  # bounds the one broadcast: two longs a range


def threshold(bits: int = FRACTION_BITS) -> int:
    """The largest signed hash that is kept."""
    return -(1 << 63) + (1 << (64 - bits)) - 1


def sketch(text: Column, words: int = WORDS, bits: int = FRACTION_BITS) -> Column:
    """Sorted array of the distinct kept hashes of the text's word shingles."""
    w = F.split(F.btrim(F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+", " ")), " ")

    def hashes(a: Column) -> Column:
        each = lambda i: F.xxhash64(*[F.get(a, i + k) for k in range(words)])
        whole = F.array(F.xxhash64(a))
        return F.when(F.size(a) < words, whole).otherwise(F.transform(F.sequence(F.lit(0), F.greatest(F.size(a) - words, F.lit(0))), each))

    # a one-element transform binds the word array once
    h = F.flatten(F.transform(F.array(w), hashes))
    kept = lambda a: F.array_sort(F.array_distinct(F.filter(a, lambda v: v <= F.lit(threshold(bits)))))
    one = lambda a: F.transform(F.array(kept(a)), lambda k: F.when(F.size(k) > 0, k).otherwise(F.array(F.array_min(a))))
    return F.flatten(F.transform(F.array(h), lambda a: F.flatten(one(a))))


def merge(a: Column, b: Column, bits: int = FRACTION_BITS) -> Column:
    """Sketch of the union of two documents' shingles."""
    both = F.array_sort(F.array_union(a, b))
    real = F.filter(both, lambda v: v <= F.lit(threshold(bits)))
    return F.when(F.size(real) > 0, real).otherwise(F.slice(both, 1, 1))


def jaccard(a: Column, b: Column) -> Column:
    """Estimated share of common shingles among all of both."""
    both = F.size(F.array_intersect(a, b))
    return both / (F.size(a) + F.size(b) - both)


def containment(a: Column, b: Column) -> Column:
    """Estimated share of a's shingles that b has too."""
    return F.size(F.array_intersect(a, b)) / F.size(a)


def as_text(s: Column) -> Column:
    """The sketch as one string: 16 hex digits for each hash, in order."""
    return F.array_join(F.transform(s, lambda v: F.lpad(F.lower(F.hex(v)), 16, "0")), "")


def place(knots: list[int], value: Column) -> Column:
    """Index of the last knot that is not above value (0 where all are): a binary search inside one expression."""
    k = F.array(*[F.lit(v).cast("long") for v in knots]) if len(knots) < 3 else F.lit(knots)
    steps = F.array(*[F.lit(1 << s) for s in reversed(range(max(1, (len(knots) - 1).bit_length())))])
    hit = lambda i, p: F.when((i + p < len(knots)) & (F.get(k, i + p) <= value), i + p).otherwise(i)
    return F.aggregate(steps, F.lit(0), hit)


def ranges(docs: DataFrame) -> tuple[Column, DataFrame]:
    """(range of a row, ends) for docs(id, ...): ends(top, to) holds the largest id of each range and the range that follows it.

    Ids are cut at approximate quantiles, so outliers and clusters of ids do
    not crowd a range; where there are more ranges than KNOTS, the space
    between two quantiles is cut in equal widths. There are at most
    MAX_RANGES, so that ends may be broadcast whatever the table's size.
    After the last range comes the first. Rows with a null id are dealt over
    ranges of their own.
    """
    n = docs.agg(F.count("id")).first()[0]
    count = max(1, min(MAX_RANGES, -(-n // IDS_PER_RANGE)))
    size = min(KNOTS, count)
    found = docs.agg(F.percentile_approx("id", [i / size for i in range(size)] + [1.0], 4 * size + 1000)).first()[0] if n else None
    knots, top = (sorted(set(found[:-1])), found[-1]) if found else ([0], 0)
    at, inner = place(knots, F.col("id")), -(-count // size)
    own = F.when(F.col("id").isNotNull(), at.cast("long"))
    if inner > 1:
        k = F.lit([*knots, top + 1])
        low, high = F.get(k, at), F.get(k, at + 1)
        share = (F.col("id").cast("double") - low.cast("double")) / F.greatest(high.cast("double") - low.cast("double"), F.lit(1.0))
        own = own * inner + F.least(F.greatest(F.floor(share * inner), F.lit(0)), F.lit(inner - 1))
    ends = docs.where("id is not null").groupBy(own.alias("range")).agg(F.max("id").alias("top"))
    over = Window.orderBy("range")  # one row a range
    whole = over.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    ends = ends.select("top", F.coalesce(F.lead("range").over(over), F.first("range").over(whole)).alias("to"))
    return F.coalesce(own, -1 - F.pmod(F.xxhash64("text"), F.lit(count))), stash(ends, "ends")


def edited_pairs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = WORDS, bits: int = FRACTION_BITS) -> DataFrame:
    """Each document beside its edited text: the last half of its code points replaced by the first as many of the next document.

    Returns (doc_id, n_chars, edited, sketch, edited_sketch, next_sketch).
    Texts move once, by range of id; inside a range the next document is the
    row before in ascending order, and the last row of each range visits the
    following one as a guest. Where rows share a doc_id, one of them (the
    largest text) stands as the next document; rows with a null doc_id stand
    alone and are their own next document.
    """
    base = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    home, ends = ranges(base)
    placed = base.withColumn("home", home).join(F.broadcast(ends), F.col("id") == F.col("top"), "left")
    visits = F.when(F.col("to").isNull(), F.array("home")).otherwise(F.array("home", "to"))
    placed = placed.select("id", "text", F.posexplode(visits).alias("visit", "range")).select("id", "text", "range", (F.col("visit") == 0).alias("own"))
    moved = placed.repartition("range").withColumn("sketch", sketch(F.col("text"), words, bits))
    before = Window.partitionBy("range").orderBy("own", "id", "text")
    alike = Window.partitionBy("range", "own", "id").orderBy("text")  # the same order: no further exchange or sort
    lagged = moved.withColumn("_text", F.lag("text").over(before)).withColumn("_sketch", F.lag("sketch").over(before))
    seen = lagged.withColumn("_text", F.first("_text").over(alike)).withColumn("_sketch", F.first("_sketch").over(alike)).where("own")
    other = lambda mine: F.when(F.col("id").isNull(), F.col(mine)).otherwise(F.col(f"_{mine}"))
    seen = seen.withColumn("n", F.char_length("text").cast("long"))
    half = F.floor(F.col("n") / 2)
    edited = F.concat(F.substring("text", F.lit(1), F.col("n") - half), F.substring(other("text"), F.lit(1), half))
    both = seen.select(F.col("id").alias("doc_id"), F.col("n").alias("n_chars"), edited.alias("edited"), "sketch", other("sketch").alias("next_sketch"))
    return both.select("doc_id", "n_chars", "edited", "sketch", sketch(F.col("edited"), words, bits).alias("edited_sketch"), "next_sketch")
