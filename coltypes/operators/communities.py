"""Community detection by a similarity threshold: greedy over candidate communities, largest first.

The candidate community of a centre is all that is similar to it. Candidates are taken in order of
size (ties: smallest member); members that are taken already are dropped; what is left must still
have the least size. Nodes may stand for several columns (weights): columns of equal vectors have
equal candidates, so they are taken together.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coltypes.operators.state import shared_dir

#: Pairs that the driver may hold; beyond, rounds on the cluster decide the same communities.
DRIVER_PAIRS = 200_000
#: Numbers in vectors that the driver may hold in place of their pairs (400 MB).
DRIVER_NUMBERS = 50_000_000
#: Similarities made at a time.
CELLS = 4_000_000


def greedy(nodes: dict[str, tuple[int, str]], pairs: list[tuple[str, str]], min_size: int = 2) -> dict[str, str]:
    """node -> community (its first member), for nodes of weight and first member; on the driver."""
    near: dict[str, set[str]] = {n: {n} for n in nodes}
    for i, j in pairs:
        near[i].add(j), near[j].add(i)
    weight = lambda members: sum(nodes[m][0] for m in members)
    order = sorted(((-weight(m), min(nodes[x][1] for x in m), nodes[c][1], c) for c, m in near.items() if weight(m) >= min_size))
    taken: dict[str, str] = {}
    for _, _, _, centre in order:
        rest = [m for m in near[centre] if m not in taken]
        if weight(rest) >= min_size:
            name = min(nodes[m][1] for m in rest)
            taken.update(dict.fromkeys(rest, name))
    return taken


def rounds(nodes: DataFrame, pairs: DataFrame, min_size: int = 2) -> DataFrame:
    """The same communities without the driver: (id, community).

    In each round every free node points to its best live candidate; a candidate to which all its
    free members point is decided. The best live candidate always is, so the loop ends.
    """
    spark = nodes.sparkSession
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(shared_dir(spark))
    member = pairs.select(F.col("i").alias("c"), F.col("j").alias("m")).union(pairs.select("j", "i")).union(nodes.select("id", "id"))
    member = member.join(nodes.toDF("m", "w", "first"), "m")
    rank = member.groupBy("c").agg(F.sum("w").alias("size"), F.min("first").alias("lead")).where(F.col("size") >= min_size)
    rank = rank.join(nodes.select(F.col("id").alias("c"), F.col("first").alias("own")), "c").select("c", F.struct((-F.col("size")).alias("s"), "lead", "own", "c").alias("rank"))
    free = member.join(rank, "c").checkpoint()
    done = []
    while not free.isEmpty():
        best = free.groupBy("m").agg(F.min("rank").alias("best"))
        seen = free.join(best, "m")
        ready = seen.groupBy("c").agg(F.bool_and(F.col("rank") == F.col("best")).alias("all"), F.sum("w").alias("left"), F.min("first").alias("community")).where("all")
        won = free.join(ready.where(F.col("left") >= min_size).select("c", "community"), "c").select(F.col("m").alias("id"), "community").checkpoint()
        done.append(won)
        free = free.join(ready.select("c"), "c", "left_anti").join(won.select(F.col("id").alias("m")), "m", "left_anti").checkpoint()
    out = spark.createDataFrame([], "id string, community string")
    for won in done:
        out = out.union(won)
    return out


def detect(nodes: DataFrame, pairs: DataFrame, min_size: int = 2) -> DataFrame:
    """(id, community) from nodes (id, weight, first) and pairs (i, j); small graphs on the driver, large ones in rounds."""
    nodes = nodes.select("id", F.col("weight").cast("long").alias("weight"), "first")
    if pairs.limit(DRIVER_PAIRS + 1).count() > DRIVER_PAIRS or nodes.limit(DRIVER_PAIRS + 1).count() > DRIVER_PAIRS:
        return rounds(nodes, pairs, min_size)
    found = greedy({r["id"]: (r["weight"], r["first"]) for r in nodes.collect()}, [(r["i"], r["j"]) for r in pairs.select("i", "j").collect()], min_size)
    return nodes.sparkSession.createDataFrame(sorted(found.items()), "id string, community string")


def _similar(a: np.ndarray, b: np.ndarray, tau: float) -> np.ndarray:
    """Which rows of two matrices of unit vectors have a cosine of ``tau`` or more, to 6 digits."""
    sim = a @ b.T
    out = sim >= tau - 1e-6
    at = np.nonzero(out)
    out[at] = np.round(sim[at], 6) >= tau
    return out


def of_vectors(vectors: DataFrame, tau: float, min_size: int = 2) -> DataFrame | None:
    """(id, community) of vectors (id, first, vec) without their pairs, the same as ``detect`` on all of them; None if the driver can't hold the vectors.

    Tasks find the size and the first member of each candidate; the driver then takes the candidates
    in order and multiplies their centres with what is still free.
    """
    spark, width = vectors.sparkSession, len((vectors.select("vec").first() or [[0.0]])[0])
    if vectors.count() * width > DRIVER_NUMBERS:
        return None
    t = vectors.select(F.col("id").cast("string").alias("id"), "first", F.transform("vec", lambda x: x.cast("double")).alias("vec")).orderBy("first", "id").toArrow()
    n, ids, firsts = len(t), t.column("id").to_pylist(), t.column("first").to_pylist()
    m = np.array(t.column("vec").combine_chunks().flatten()).reshape(n, width) if n else np.zeros((0, width))
    norm = np.linalg.norm(m, axis=1)
    m = m / np.where(norm > 0, norm, 1)[:, None]
    shared, step = spark.sparkContext.broadcast(m), max(1, CELLS // max(1, n))

    def sized(batches):
        for b in batches:
            for begin in b.column("id").to_pylist():
                near = _similar(shared.value[begin : begin + step], shared.value, tau)
                near[np.arange(len(near)), np.arange(begin, begin + len(near))] = True
                yield pa.record_batch([pa.array(np.arange(begin, begin + len(near))), pa.array(near.sum(axis=1)), pa.array(near.argmax(axis=1))], ["at", "size", "lead"])

    dealt = spark.range(0, max(n, 1), step, max(1, min(-(-n // step), 4 * spark.sparkContext.defaultParallelism)))
    got = dealt.where(F.lit(n > 0)).mapInArrow(sized, "at long, size long, lead long").toArrow()
    at, size, lead = (np.array(got.column(c)) for c in ("at", "size", "lead"))
    keep = size >= min_size
    order = at[keep][np.lexsort((at[keep], lead[keep], -size[keep]))]
    taken, free, begin = np.full(n, -1), np.arange(n), 0
    while begin < len(order) and len(free) >= min_size:
        centres = order[begin : begin + max(16, min(2048, CELLS // len(free)))]
        near = _similar(m[centres], m[free], tau) | (centres[:, None] == free[None, :])
        for c in np.nonzero(near.sum(axis=1) >= min_size)[0]:
            rest = free[near[c]]
            rest = rest[taken[rest] < 0]
            if len(rest) >= min_size:
                taken[rest] = rest[0]
        free, begin = free[taken[free] < 0], begin + len(centres)
    shared.unpersist()
    return spark.createDataFrame([(ids[k], firsts[taken[k]]) for k in np.nonzero(taken >= 0)[0].tolist()], "id string, community string")


def members_of(found: dict[str, str]) -> dict[str, list[str]]:
    out: dict[str, list[str]] = defaultdict(list)
    for node, community in sorted(found.items()):
        out[community].append(node)
    return dict(out)
