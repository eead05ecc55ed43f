"""Transitions, alias tables, walks and context pairs, distributed."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F, types as T

from ..functions.rng import draw, u01
from ..plans.storage import drop_stash, stash
from .graph import arcs
from .local import alias_table
from .partition import numbered

BLOCK = 65_536  # elements of one node's alias block
DRAWS = {"portable": u01, "bulk": draw}  # md5 draws have a SQL form; bulk draws are cheaper and equal those of numpy


def transitions(edges: DataFrame) -> DataFrame:
    """(src, dst, prob) from edges(src, dst, w): the weight's share among those at src."""
    a = arcs(edges)
    return a.join(a.groupBy("src").agg(F.sum("w").alias("total")), "src").select("src", "dst", (F.col("w") / F.col("total")).alias("prob"))


def alias_tables(trans: DataFrame) -> DataFrame:
    """(src, slot, own, alias, p_keep, deg): one row for each element; nodes of over BLOCK elements use alias_blocks()."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("dst")
        keep, to = alias_table(pdf["prob"].to_numpy())
        own = pdf["dst"].to_numpy()
        return pd.DataFrame({"src": pdf["src"].to_numpy(), "slot": np.arange(len(own), dtype=np.int32), "own": own, "alias": own[to], "p_keep": keep, "deg": np.int32(len(own))})

    return trans.select(F.col("src").cast("long"), F.col("dst").cast("long"), "prob").groupBy("src").applyInPandas(run, "src long, slot int, own long, alias long, p_keep double, deg int")


def alias_blocks(trans: DataFrame, block: int = BLOCK) -> tuple[DataFrame, DataFrame]:
    """For hubs: (alias over blocks, alias inside each block). No task holds more than `block` elements of a node."""
    nb = F.greatest(F.ceil(F.col("n") / block), F.lit(1))
    size = trans.groupBy("src").agg(F.count("*").alias("n"))
    cut = trans.join(size, "src").withColumn("block", F.pmod(F.xxhash64("dst"), nb).cast("long"))
    mass = cut.groupBy("src", "block").agg(F.sum("prob").alias("prob"))
    outer = alias_tables(mass.select("src", F.col("block").alias("dst"), "prob"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("dst")
        keep, to = alias_table(pdf["prob"].to_numpy())
        own = pdf["dst"].to_numpy()
        return pd.DataFrame({"src": pdf["src"].to_numpy(), "block": pdf["block"].to_numpy(), "slot": np.arange(len(own), dtype=np.int32), "own": own, "alias": own[to], "p_keep": keep, "deg": np.int32(len(own))})

    inner = cut.select("src", "block", "dst", "prob").groupBy("src", "block").applyInPandas(run, "src long, block long, slot int, own long, alias long, p_keep double, deg int")
    return outer, inner


def alias_mass(alias: DataFrame) -> DataFrame:
    """(src, dst, prob) rebuilt from the tables."""
    each = alias.select("src", F.explode(F.array(F.struct(F.col("own").alias("dst"), F.col("p_keep").alias("p")), F.struct(F.col("alias").alias("dst"), (1 - F.col("p_keep")).alias("p")))).alias("e"), "deg")
    return each.groupBy("src", F.col("e.dst").alias("dst")).agg((F.sum("e.p") / F.first("deg")).alias("prob"))


def settled(prob: Column) -> Column:
    """A rebuilt probability without the last bits of its sums, so that a tie of a later rounding is one again."""
    return F.round(prob, 13)


def starts(nodes: DataFrame, per_node: int) -> DataFrame:
    return nodes.select(F.explode(F.sequence(F.lit(0), F.lit(per_node - 1))).alias("nth"), F.col("node").alias("start")).withColumn("path", F.array("start")).withColumn("cur", F.col("start"))


def _draws(seed: int, step: int, draws: str = "portable") -> tuple:
    u = DRAWS[draws]
    return u("slot", seed, F.col("start"), F.col("nth"), F.lit(step)), u("keep", seed, F.col("start"), F.col("nth"), F.lit(step))


def _extended(nxt: Column) -> list[Column]:
    """The walk's columns after a step to nxt; null ends it."""
    return ["nth", "start", F.when(nxt.isNull(), F.col("path")).otherwise(F.concat("path", F.array(nxt))).alias("path"), nxt.alias("cur")]


def weighted(alias: DataFrame, nodes: DataFrame, per_node: int, length: int, seed: int = 1, draws: str = "portable") -> DataFrame:
    """(start, nth, path): each step is an equi-join of the walks on (node, slot); a walk without neighbours stops."""
    deg = stash(alias.where("slot = 0").select(F.col("src").alias("cur"), "deg"), "deg")
    state = starts(nodes, per_node)
    old: DataFrame | None = None
    for step in range(1, length):
        u, v = _draws(seed, step, draws)
        slotted = state.join(deg, "cur", "left").withColumn("slot", F.least(F.floor(u * F.col("deg")), F.col("deg") - 1).cast("int"))
        drawn = slotted.join(alias.select(F.col("src").alias("cur"), "slot", "own", "alias", "p_keep"), ["cur", "slot"], "left")
        state = drawn.select(*_extended(F.when(v < F.col("p_keep"), F.col("own")).otherwise(F.col("alias"))))
        if step % 4 == 0:
            state = stash(state, "walk")
            if old is not None:
                drop_stash(old)
            old = state
    return state.select("start", "nth", "path")


def weighted_blocked(outer: DataFrame, inner: DataFrame, nodes: DataFrame, per_node: int, length: int, seed: int = 1, draws: str = "bulk") -> DataFrame:
    """Walks by two draws a step: a block of the node's elements, then an element of the block (tables of alias_blocks())."""
    u = DRAWS[draws]
    top = stash(outer.where("slot = 0").select(F.col("src").alias("cur"), F.col("deg").alias("blocks")), "deg")
    low = stash(inner.where("slot = 0").select(F.col("src").alias("cur"), "block", "deg"), "deg")
    state = starts(nodes, per_node)
    for step in range(1, length):
        a, b, c, e = (u(p, seed, F.col("start"), F.col("nth"), F.lit(step)) for p in ("block", "block_keep", "slot", "keep"))
        s = state.join(top, "cur", "left").withColumn("slot", F.least(F.floor(a * F.col("blocks")), F.col("blocks") - 1).cast("int"))
        s = s.join(outer.select(F.col("src").alias("cur"), "slot", "own", "alias", "p_keep"), ["cur", "slot"], "left")
        s = s.select("nth", "start", "path", "cur", F.when(b < F.col("p_keep"), F.col("own")).otherwise(F.col("alias")).alias("block"))
        s = s.join(low, ["cur", "block"], "left").withColumn("slot", F.least(F.floor(c * F.col("deg")), F.col("deg") - 1).cast("int"))
        s = s.join(inner.select(F.col("src").alias("cur"), "block", "slot", "own", "alias", "p_keep"), ["cur", "block", "slot"], "left")
        state = stash(s.select(*_extended(F.when(e < F.col("p_keep"), F.col("own")).otherwise(F.col("alias")))), "walk")
    return state.select("start", "nth", "path")


def slots(edges: DataFrame) -> DataFrame:
    """(src, slot, dst, deg): neighbours numbered in id order. Arcs are ranked over range partitions, so a hub's are spread over tasks."""
    r = stash(numbered(arcs(edges.select("src", "dst")), ["src", "dst"]), "slots")
    own = r.groupBy("src").agg(F.min("rank").alias("first"), F.count("*").cast("int").alias("deg"))
    return r.join(own, "src").select("src", (F.col("rank") - F.col("first")).cast("int").alias("slot"), "dst", "deg")


def uniform(edges: DataFrame, nodes: DataFrame, per_node: int, length: int, seed: int = 1, draws: str = "portable") -> DataFrame:
    """Walks on an unweighted graph: slots number the sorted neighbours, no alias needed."""
    table = slots(edges).select("src", "slot", F.col("dst").alias("own"), F.col("dst").alias("alias"), F.lit(1.0).alias("p_keep"), "deg")
    return weighted(stash(table, "slots"), nodes, per_node, length, seed, draws)


def by_cdf(trans: DataFrame, nodes: DataFrame, per_node: int, length: int, seed: int = 1) -> DataFrame:
    """The scanning baseline of the alias draw: cumulative intervals and a range condition."""
    run = Window.partitionBy("src").orderBy("dst").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    cum = trans.withColumn("hi", F.round(F.sum("prob").over(run), 9)).withColumn("lo", F.coalesce(F.lag("hi").over(Window.partitionBy("src").orderBy("dst")), F.lit(0.0)))
    cum = stash(cum.select(F.col("src").alias("cur"), F.col("dst").alias("nxt"), "lo", "hi"), "cdf")
    state = starts(nodes, per_node)
    for step in range(1, length):
        u, _ = _draws(seed, step)
        s = state.withColumn("u", u)
        hit = s.join(cum, (s["cur"] == cum["cur"]) & (s["u"] >= cum["lo"]) & (s["u"] < cum["hi"]), "left").drop(cum["cur"])
        state = hit.select("nth", "start", F.when(F.col("nxt").isNull(), F.col("path")).otherwise(F.concat("path", F.array("nxt"))).alias("path"), F.col("nxt").alias("cur"))
    return state.select("start", "nth", "path")


def _second_order(prev: Column, cand: Column, near: Column, p: float, q: float) -> Column:
    top = max(1 / p, 1.0, 1 / q)
    return F.when(prev.isNull(), top).when(cand == prev, 1 / p).when(near, 1.0).otherwise(1 / q)


STATES, CANDIDATES = 2_000_000, 1 << 22  # states of one task, and candidates that it looks at together


def second_order_step(edges: DataFrame, state: DataFrame, u: Column, p: float, q: float, blocks: int | None = None) -> DataFrame:
    """state(cur, prev, ...) with the next node `cand`, drawn by u from the whole second-order distribution: the running sum of the neighbours' case weights.

    A state meets the neighbours of both its nodes in the task of their two
    blocks. Its candidates live there, a bounded number at a time, so none is
    written or sent. The number of blocks follows from arcs and states.
    """
    a = arcs(edges.select("src", "dst"))
    if blocks is None:
        blocks = max(4, math.ceil(a.count() / STATES), math.ceil(math.sqrt(state.count() / STATES)))
    of = lambda c: F.pmod(F.xxhash64(F.lit(5), c), F.lit(blocks)).cast("int")
    near = F.when(F.col("prev").isNull(), of(F.col("cur"))).otherwise(of(F.col("prev")))
    some = state.withColumn("u", u.cast("double")).withColumn("i", near).withColumn("j", of(F.col("cur")))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    own = a.withColumn("own", of(F.col("src")))
    lists = own.withColumn("i", every).select("i", F.col("own").alias("j"), "src", "dst")
    lists = lists.unionAll(own.withColumn("j", every).where("own <> j").select(F.col("own").alias("i"), "j", "src", "dst"))
    names = [*state.columns]
    schema = T.StructType([*state.schema.fields, T.StructField("cand", T.LongType())])

    def draw_all(s: pa.Table, e: pa.Table) -> pa.Table:
        if not s.num_rows or not e.num_rows:
            return pa.table({f.name: pa.nulls(0, t) for f, t in zip(schema.fields, (*(s.schema.field(c).type for c in names), pa.int64()))})
        src, dst = e.column("src").to_numpy(), e.column("dst").to_numpy()
        order = np.lexsort((dst, src))
        ids = np.unique(np.concatenate([src, dst]))
        src, dst = np.searchsorted(ids, src[order]), np.searchsorted(ids, dst[order])
        ptr = np.searchsorted(src, np.arange(len(ids) + 1))
        key = src * len(ids) + dst
        cur = s.column("cur").to_numpy()
        at = np.minimum(np.searchsorted(ids, cur), len(ids) - 1)
        deg = np.where(ids[at] == cur, np.diff(ptr)[at], 0)
        none = s.column("prev").is_null().to_numpy(zero_copy_only=False)
        prev = s.column("prev").fill_null(0).to_numpy()
        back = np.minimum(np.searchsorted(ids, prev), len(ids) - 1)
        back = np.where(none | (ids[back] != prev), -1, back)
        goal = s.column("u").to_numpy()
        live = np.flatnonzero(deg > 0)
        take = np.full(len(cur), -1, np.int64)
        ends = np.cumsum(deg[live])
        lo = 0
        while lo < len(live):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + CANDIDATES, side="right")))
            r = live[lo:hi]
            d = deg[r]
            first = np.cumsum(d) - d
            of_row = np.repeat(np.arange(len(r)), d)
            c = dst[np.arange(len(of_row)) - first[of_row] + ptr[at[r]][of_row]]
            b = back[r][of_row]
            k = b * len(ids) + c
            spot = np.minimum(np.searchsorted(key, k), len(key) - 1)
            w = np.where(b == c, 1 / p, np.where((b >= 0) & (key[spot] == k), 1.0, 1 / q))
            w[none[r][of_row]] = 1.0
            run = np.cumsum(w)
            base = (run - w)[first]
            run -= base[of_row]
            total = run[first + d - 1]
            under = np.add.reduceat((run <= (goal[r] * total)[of_row]).astype(np.int64), first)
            take[r] = ids[c[first + np.minimum(under, d - 1)]]
            lo = hi
        out = s.select(names).take(pa.array(live))
        return out.append_column("cand", pa.array(take[live]))

    return some.groupBy("i", "j").cogroup(lists.groupBy("i", "j")).applyInArrow(draw_all, schema)


def biased(edges: DataFrame, nodes: DataFrame, per_node: int, length: int, p: float = 1.0, q: float = 1.0, seed: int = 1, tries: int = 6) -> DataFrame:
    """Second-order walks: uniform proposals are accepted by the case weight (an edge flag prev - candidate comes by a left join); whoever is refused `tries` times draws from the whole distribution.

    Two proposals are offered at once, the others to those refused only. The
    distribution is exact whatever p and q are.
    """
    table = stash(slots(edges), "slots")
    deg = table.where("slot = 0").select(F.col("src").alias("cur"), "deg")
    flag = table.select(F.col("src").alias("prev"), F.col("dst").alias("cand"), F.lit(True).alias("near"))
    top = max(1 / p, 1.0, 1 / q)
    state = starts(nodes, per_node).withColumn("prev", F.lit(None).cast("long"))
    old: DataFrame | None = None
    for step in range(1, length):
        def offered(some: DataFrame, first: int, end: int) -> DataFrame:
            offer = some.join(deg, "cur").withColumn("try", F.explode(F.array(*[F.lit(t) for t in range(first, end)])))
            key = [F.col("start"), F.col("nth"), F.lit(step), F.col("try")]
            offer = offer.withColumn("slot", F.least(F.floor(draw("slot", seed, *key) * F.col("deg")), F.col("deg") - 1).cast("int"))
            cand = offer.join(table.select(F.col("src").alias("cur"), "slot", F.col("dst").alias("cand")), ["cur", "slot"]).join(flag, ["prev", "cand"], "left")
            ok = cand.where(draw("keep", seed, *key) * top < _second_order(F.col("prev"), F.col("cand"), F.col("near"), p, q))
            return ok.groupBy("start", "nth").agg(F.min_by("cand", "try").alias("cand"))

        early = min(2, tries)
        found = stash(offered(state, 0, early), "try")
        live = state.join(deg.select("cur"), "cur", "left_semi")
        left = live.join(found, ["start", "nth"], "left_anti")
        if tries > early:
            found = stash(found.unionByName(offered(left, early, tries)), "try")
            left = live.join(found, ["start", "nth"], "left_anti")
        rest = second_order_step(edges, left.select("start", "nth", "cur", "prev"), draw("rest", seed, F.col("start"), F.col("nth"), F.lit(step)), p, q)
        found = found.unionByName(rest.select("start", "nth", "cand"))
        cur = F.col("cur").alias("prev")
        state = stash(state.join(found, ["start", "nth"], "left").select(*_extended(F.col("cand")), cur), "walk")
        if old is not None:
            drop_stash(old)
        old = state
    return state.select("start", "nth", "path")


def context_pairs(walks: DataFrame, window: int) -> DataFrame:
    """(center, context, n): pairs within `window` places of one path, counted; built inside each row, then combined."""
    near = F.flatten(
        F.transform(F.sequence(F.lit(0), F.size("path") - 1), lambda i: F.transform(
            F.filter(F.sequence(F.greatest(i - window, F.lit(0)), F.least(i + window, F.size("path") - 1)), lambda j: j != i),
            lambda j: F.struct(F.get("path", i).alias("center"), F.get("path", j).alias("context"))))
    )
    return walks.select(F.explode(near).alias("p")).groupBy("p.center", "p.context").agg(F.count("*").alias("n"))


def walk_rows(walks: DataFrame) -> DataFrame:
    return walks.select("start", "nth", F.array_join(F.col("path").cast("array<string>"), ",").alias("path"))
