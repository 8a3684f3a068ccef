"""Typical paths: candidates that grow edge by edge, all at once, and the removal of redundant ones.

Draws are md5 texts of (seed, candidate, step, edge), so that any engine repeats them.
"""

from __future__ import annotations

import warnings

from pyspark.sql import DataFrame, Window, functions as F

from ..functions.shared import cut

L_MIN, L_MAX = 2000, 3000


def draw(seed: int, cand: str, step, eid: str):
    return F.md5(F.concat_ws("|", F.lit(seed), F.col(cand), step, F.col(eid)).cast("binary"))


def starts(edges: DataFrame, regioned: DataFrame, quotas: DataFrame, seed: int, oversample: int = 4, l_min: int = L_MIN, l_max: int = L_MAX, again: int = 0) -> DataFrame:
    """First edges: candidates are numbered by (region, turn); each has a length target drawn in [l_min, l_max].

    `again` draws the turns after so many times those of the first draw.
    """
    size = (F.col("quota") * oversample).cast("int")
    turn = quotas.filter("quota > 0").select("region", F.explode(F.sequence(size * again, size * (again + 1) - 1)).alias("turn"))
    cand = turn.select("region", (F.col("region") * 1000000 + F.col("turn")).cast("bigint").alias("cand"))
    eta = F.lit(l_min) + F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(seed), F.col("cand"), F.lit("eta")).cast("binary")), 1, 8), 16, 10).cast("bigint") % (l_max - l_min + 1)
    placed = edges.join(regioned.select(F.col("vid").alias("src"), "region"), "src")
    first = cand.join(placed, "region").groupBy("cand", "region").agg(F.min_by(F.struct("eid", "dst", "length_m"), draw(seed, "cand", F.lit(0), "eid")).alias("e"))
    return first.select("cand", "region", eta.alias("eta"), F.col("e.dst").alias("head"), F.col("e.length_m").alias("length"), F.array("e.eid").alias("edges"))


def grow(edges: DataFrame, begun: DataFrame, seed: int, cvs: DataFrame | None = None, floor: float | None = None, l_max: int = L_MAX, no_uturn: bool = False, every: int = 3) -> DataFrame:
    """(cand, region, eta, head, length, edges) after growing past the target, or to a dead end.

    Without `cvs` the next edge is drawn; with them it is the most variable one, not below `floor`. A path
    never repeats an edge. A round is one join on the head vertex and one aggregate by candidate; lineage is
    cut every few rounds, so plans stay small.
    """
    out_edges = edges.select(F.col("src").alias("head"), F.col("eid").alias("next"), F.col("dst").alias("to"), F.col("length_m").alias("more"), F.col("src").alias("from"))
    if cvs is not None:
        out_edges = out_edges.join(cvs.select(F.col("eid").alias("next"), "cv"), "next").filter(F.col("cv") >= (floor or 0.0))
    came_from = edges.select(F.col("eid").alias("begin"), F.col("src").alias("prev"))
    done, live, step = None, begun.withColumn("begin", F.element_at("edges", 1)).join(came_from, "begin").drop("begin"), 0
    while True:
        for _ in range(every):
            step += 1
            fits = live.filter("length <= eta").join(out_edges, "head").filter(~F.array_contains("edges", F.col("next")))
            if no_uturn:
                fits = fits.filter("to <> prev")
            order = draw(seed, "cand", F.lit(step), "next") if cvs is None else F.struct((-F.col("cv")).alias("a"), F.col("next").alias("b"))
            grown = fits.groupBy("cand").agg(F.min_by(F.struct("next", "to", "more", "from"), order).alias("n"))
            live = live.join(grown, "cand", "left").select(
                "cand", "region", "eta", F.coalesce("n.to", "head").alias("head"), (F.col("length") + F.coalesce("n.more", F.lit(0))).alias("length"),
                F.when(F.col("n").isNull(), F.col("edges")).otherwise(F.array_append("edges", F.col("n.next"))).alias("edges"), F.coalesce("n.from", "prev").alias("prev"),
                (F.col("n").isNull() | (F.col("length") > F.col("eta"))).alias("ended"),
            )
            step_live = live
            live = step_live.drop("ended")
        state = cut(step_live)
        over = state.filter("ended or length > eta").drop("ended", "prev")
        done = over if done is None else done.unionByName(over)
        live = state.filter("not ended and length <= eta").drop("ended")
        if live.isEmpty():
            return done


def valid(grown: DataFrame, l_min: int = L_MIN, l_max: int = L_MAX) -> DataFrame:
    return grown.filter(F.col("length").between(l_min, l_max))


def overlaps(paths: DataFrame) -> DataFrame:
    """(region, a, b, jaccard) of candidates a < b of a region that share an edge."""
    e = paths.select("region", "cand", F.size("edges").alias("n"), F.explode("edges").alias("eid"))
    x, y = e.select("region", "eid", F.col("cand").alias("a"), F.col("n").alias("na")), e.select("region", "eid", F.col("cand").alias("b"), F.col("n").alias("nb"))
    both = x.join(y, ["region", "eid"]).filter("a < b").groupBy("region", "a", "b", "na", "nb").agg(F.count("*").alias("m"))
    return both.select("region", "a", "b", F.round(F.col("m") / (F.col("na") + F.col("nb") - F.col("m")), 6).alias("jaccard"))


def dedup(paths: DataFrame, quotas: DataFrame, max_jaccard: float = 0.3) -> DataFrame:
    """Typical paths: candidates in order, without those too similar to one kept before, up to each quota."""
    close = overlaps(paths).filter(F.col("jaccard") > max_jaccard).groupBy(F.col("b").alias("cand")).agg(F.collect_list("a").alias("near"))
    rows = paths.join(close, "cand", "left").join(quotas, "region")

    def choose(key, table):
        table = table.sort_by("cand")
        limit, kept, pick = table.column("quota")[0].as_py(), set(), []
        for i, (c, near) in enumerate(zip(table.column("cand").to_pylist(), table.column("near").to_pylist())):
            if len(kept) < limit and not kept.intersection(near or ()):
                kept.add(c)
                pick.append(i)
        return table.take(pick).select(["cand", "region", "length", "edges"])

    return rows.select("cand", "region", "length", "edges", "near", "quota").groupBy("region").applyInArrow(choose, "cand bigint, region int, length bigint, edges array<bigint>")


def as_paths(typical: DataFrame) -> DataFrame:
    """(pid, seq, eid)."""
    return typical.select(F.col("cand").alias("pid"), F.posexplode("edges").alias("seq", "eid"))


def coverage(typical_paths: DataFrame, edges: DataFrame) -> DataFrame:
    """One row: shares of edges, vertices and length that the paths touch."""
    used = edges.join(typical_paths.select("eid").distinct(), "eid", "left_semi")
    touched = used.select("src").union(used.select("dst")).distinct().agg(F.count("*").alias("v"))
    every = edges.select("src").union(edges.select("dst")).distinct().agg(F.count("*").alias("vall"))
    sums = edges.agg(F.count("*").alias("eall"), F.sum("length_m").alias("lall")).crossJoin(used.agg(F.count("*").alias("e"), F.coalesce(F.sum("length_m"), F.lit(0)).alias("l")))
    return sums.crossJoin(touched).crossJoin(every).select(*[F.round(F.col(a) / F.col(b), 6).alias(c) for a, b, c in (("e", "eall", "edge_share"), ("v", "vall", "vertex_share"), ("l", "lall", "length_share"))])


def path_cv(costs: DataFrame) -> DataFrame:
    """(pid, cv) of travel times over snapshots."""
    from .edgevec import cv

    return cv(costs.select(F.col("pid").alias("eid"), F.col("d_ms").alias("w_ms"))).withColumnRenamed("eid", "pid")


def select(kind: str, edges: DataFrame, regioned: DataFrame, pnum: int, cvs: DataFrame | None = None, seed: int = 42, top_share: float = 0.3, floor_share: float = 0.5, max_jaccard: float = 0.3, draws: int = 6, **kw) -> DataFrame:
    """Typical paths of one kind: random, constrained (on the most variable edges only) or greedy.

    Regions that stay below their quota draw further turns, as walks may end early or be too much alike, until a draw
    adds none or `draws` are made; what is still missing then is told by a warning.
    """
    from .edgevec import cv_filter
    from .regions import quota

    quotas = quota(regioned, pnum)
    if kind == "constrained":
        edges = edges.join(cv_filter(cvs, top_share=top_share), "eid", "left_semi")
    floor = cv_filter(cvs, top_share=floor_share).agg(F.min("cv")).first()[0] if kind == "greedy" else None
    edges, quotas, short, every, had = cut(edges), cut(quotas), None, None, -1
    for again in range(draws):
        begun = starts(edges, regioned, quotas if short is None else short, seed, again=again)
        grown = cut(valid(grow(edges, begun, seed, cvs if kind == "greedy" else None, floor, **kw)))
        every = grown if every is None else every.unionByName(grown)
        kept = cut(dedup(every, quotas, max_jaccard))
        have = kept.groupBy("region").agg(F.count("*").alias("have"))
        short = cut(quotas.join(have, "region", "left").filter(F.coalesce("have", F.lit(0)) < F.col("quota")).select("region", "quota"))
        if short.isEmpty():
            return kept
        found = kept.count()
        if found == had:
            break
        had = found
    warnings.warn(f"{pnum - had} of {pnum} typical paths were not found in {again + 1} draws", stacklevel=2)
    return kept
