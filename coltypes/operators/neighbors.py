"""All pairs of vectors with cosine at or above a threshold, and value overlap as the traditional counterpart."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.ml.feature import BucketedRandomProjectionLSH
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coltypes.functions.exprs import cosine
from coltypes.operators.valueindex import edges


def _collapsed(vectors: DataFrame, digits: int = 9) -> tuple[DataFrame, DataFrame]:
    """Equal vectors as one row: (id, vec) of the smallest id, and (id, same) membership."""
    keyed = vectors.select("id", "vec", F.transform("vec", lambda x: F.round(x.cast("double"), digits)).alias("k"))
    first = keyed.groupBy("k").agg(F.min("id").alias("id"))
    return keyed.join(first.select("id"), "id", "left_semi").select("id", "vec"), keyed.join(first.withColumnRenamed("id", "rep"), "k").select("rep", "id")


def exact(vectors: DataFrame, tau: float) -> DataFrame:
    """(i, j, sim) by a nested-loop join over vectors; for thousands of columns."""
    a = vectors.select(F.col("id").alias("i"), F.col("vec").alias("a"))
    b = vectors.select(F.col("id").alias("j"), F.col("vec").alias("b"))
    return a.join(b, F.col("i") < F.col("j")).select("i", "j", cosine(F.col("a"), F.col("b")).alias("sim")).where(F.round("sim", 6) >= tau)


#: Vectors of one side of a product.
SIDE = 1024


def _products(tau: float):
    """Of a group of one or two blocks, the pairs at ``tau`` or above, by products of SIDE vectors; between blocks only where there are two."""
    def run(t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        ids, blocks = np.array(t.column("id").to_pylist(), dtype=object), t.column("b").to_numpy()
        m = np.array(t.column("vec").combine_chunks().flatten(), dtype=float).reshape(len(ids), -1)
        norm = np.linalg.norm(m, axis=1)
        m = m / np.where(norm > 0, norm, 1)[:, None]
        one = t.column("x")[0].as_py() == t.column("y")[0].as_py()
        left = np.arange(len(ids)) if one else np.nonzero(blocks == blocks.min())[0]
        right = left if one else np.nonzero(blocks > blocks.min())[0]
        found = []
        for at in range(0, len(left), SIDE):
            a = left[at : at + SIDE]
            for to in range(at if one else 0, len(right), SIDE):
                b = right[to : to + SIDE]
                sim = m[a] @ m[b].T
                fit = np.round(sim, 6) >= tau
                p, q = np.nonzero(fit & (a[:, None] < b[None, :]) if one else fit)
                found.append((a[p], b[q], sim[p, q]))
        p, q, sim = (np.concatenate(c) for c in zip(*found, (left[:0], left[:0], np.zeros(0)), strict=True))
        i, j = ids[p], ids[q]
        swap = np.array([a > b for a, b in zip(i, j, strict=True)], bool)
        i, j = np.where(swap, j, i), np.where(swap, i, j)
        return pa.table({"i": pa.array(i, pa.string()), "j": pa.array(j, pa.string()), "sim": pa.array(sim, pa.float64())})

    return run


def _multiplied(held: DataFrame, tau: float, size: int, *by: str) -> DataFrame:
    """(i, j, sim) of vectors (id, vec, c) that agree in ``by``, where c is how many agree: c / size blocks, each pair of them one group."""
    n = F.ceil(F.col("c") / size).cast("long")
    placed = held.withColumn("n", n).withColumn("b", F.pmod(F.xxhash64("id"), F.col("n")).cast("int"))
    sides = F.transform(F.sequence(F.lit(0).cast("long"), F.col("n") - 1), lambda o: F.struct(F.least("b", o).alias("x"), F.greatest("b", o).alias("y")))
    dealt = placed.select(*by, F.col("id").cast("string").alias("id"), "vec", "b", F.explode(sides).alias("g")).select(*by, "id", "vec", "b", "g.x", "g.y")
    return dealt.groupBy(*by, "x", "y").applyInArrow(_products(tau), "i string, j string, sim double")


def _doubles(vectors: DataFrame) -> DataFrame:
    return vectors.select("id", F.transform("vec", lambda x: x.cast("double")).alias("vec"))


def block(vectors: DataFrame, tau: float, size: int | None = None) -> DataFrame:
    """(i, j, sim) by products of vector blocks: every pair of blocks is one group of at most two blocks.

    A vector goes to as many groups as there are blocks, so blocks grow with the vectors: 20 of them up to 16 SIDE vectors each.
    """
    n = max(1, vectors.count())
    return _multiplied(_doubles(vectors).withColumn("c", F.lit(n)), tau, size or min(16 * SIDE, max(SIDE, -(-n // 20))))


def hyperplanes(vectors: DataFrame, tau: float, recall: float = 0.95, size: int = SIDE, seed: int = 7) -> DataFrame:
    """(i, j, sim) of vectors that lie on the same sides of random planes in some table, checked exactly.

    A pair at angle t agrees in a bit with probability 1 - t / pi. Bits grow with the logarithm of the
    number of vectors, so buckets stay small, and there are as many tables as a pair just at ``tau``
    needs to be found with probability ``recall``. A large bucket is multiplied in blocks.
    """
    n, width = vectors.count(), len((vectors.select("vec").first() or [[0.0]])[0])
    bits = max(2, int(np.ceil(np.log2(max(4, n / (size / 4))))))
    agree = (1 - np.arccos(min(1.0, max(-1.0, tau))) / np.pi) ** bits
    tables = max(1, int(np.ceil(np.log(1 - recall) / np.log1p(-min(agree, 1 - 1e-9)))))

    def sketch(batches):
        planes = np.random.default_rng(seed).standard_normal((tables * bits, width)).T
        place = 1 << np.arange(bits)
        for b in batches:
            m = np.array(b.column("vec").to_pylist(), dtype=float).reshape(-1, width)
            keys = ((m @ planes > 0).reshape(len(m), tables, bits) * place).sum(axis=2)
            yield pa.record_batch([b.column("id"), b.column("vec"), pa.array(list(keys), pa.list_(pa.int64()))], ["id", "vec", "keys"])

    held = _doubles(vectors).withColumn("id", F.col("id").cast("string"))
    keyed = held.mapInArrow(sketch, "id string, vec array<double>, keys array<bigint>").select("id", "vec", F.posexplode("keys").alias("table", "key"))
    sizes = keyed.groupBy("table", "key").agg(F.count("*").alias("c")).where("c > 1")
    return _multiplied(keyed.join(sizes, ["table", "key"]), tau, size, "table", "key").dropDuplicates(["i", "j"])


def lsh(vectors: DataFrame, tau: float, tables: int = 8, width: float = 0.5) -> DataFrame:
    """(i, j, sim): candidates by random projections of unit vectors (squared distance = 2 - 2 cosine), then an exact check."""
    norm = F.sqrt(F.aggregate("vec", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double")))
    unit = vectors.withColumn("norm", norm).where("norm > 0").select("id", "vec", array_to_vector(F.transform("vec", lambda x: x.cast("double") / F.col("norm"))).alias("v"))
    model = BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=width, numHashTables=tables, seed=7).fit(unit)
    near = model.approxSimilarityJoin(unit, unit, float(np.sqrt(2 - 2 * tau) + 1e-6), "d")
    rows = near.where("datasetA.id < datasetB.id").select(F.col("datasetA.id").alias("i"), F.col("datasetB.id").alias("j"), cosine(F.col("datasetA.vec"), F.col("datasetB.vec")).alias("sim"))
    return rows.where(F.round("sim", 6) >= tau)


def pairs(vectors: DataFrame, tau: float, method: str = "auto") -> DataFrame:
    """auto: all pairs, by blocks, however many vectors there are; the approximate ways only if named."""
    return {"auto": block, "exact": exact, "block": block, "hyperplanes": hyperplanes, "lsh": lsh}[method](vectors, tau)


def jaccard(values: DataFrame, tau: float) -> DataFrame:
    """(i, j, sim): columns whose value sets overlap by Jaccard ``tau``; disjoint pairs never meet.

    Values held by the same columns are one edge with a count, so a pair is made once for each
    different set of columns and not for each value.
    """
    v = values.select("column_id", "value").distinct()
    sizes = v.groupBy("column_id").agg(F.count("*").alias("size"))
    held = edges(v, "column_id", ["value"])
    a, b = held.withColumnRenamed("column_id", "i"), held.select(F.col("column_id").alias("j"), "e1", "e2")
    both = a.join(b, ["e1", "e2"]).where("i < j").groupBy("i", "j").agg(F.sum("n_values").alias("both"))
    out = both.join(sizes.toDF("i", "si"), "i").join(sizes.toDF("j", "sj"), "j")
    return out.select("i", "j", (F.col("both") / (F.col("si") + F.col("sj") - F.col("both"))).alias("sim")).where(F.round("sim", 6) >= tau)


def theta_overlap(values: DataFrame, pairs: DataFrame) -> DataFrame:
    """(i, j, overlap): estimated Jaccard of given column pairs, from one mergeable sketch of some 100 kB at most per column."""
    held = values.groupBy("column_id").agg(F.expr("theta_sketch_agg(value, 14)").alias("s"))
    both = pairs.select("i", "j").join(held.toDF("i", "s"), "i").join(held.toDF("j", "t"), "j")
    shared, total = F.expr("theta_sketch_estimate(theta_intersection(s, t))"), F.expr("theta_sketch_estimate(theta_union(s, t, 14))")
    return both.select("i", "j", F.coalesce(F.try_divide(shared, total), F.lit(0.0)).alias("overlap"))
