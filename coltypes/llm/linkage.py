"""Connected components over candidate buckets, without the pairs inside a bucket.

A bucket holds keys that may be linked; its smallest key is its hub. Keys are compared in units of
bounded size, in memory, and a unit returns only links that join parts of its own, so the rows made
stay linear in the keys of a unit.

First round: each key goes to the home of the hub that it meets in most buckets. A large home is cut
into blocks, each with the hub in it; small homes share units. What is linked joins into parts.

Second round, for buckets that still hold several parts: each key goes to the cell of the smallest
hub that it or a key of its buckets meets. Within a cell a part with many keys has blocks of its
own, the rest is mixed, so two blocks are compared only if they do not lie in one part already. Two
cells are compared where they share a bucket. So every pair that shares a bucket has been compared
or was connected before.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from coltypes.llm import common

#: A home or cell of fewer keys than 1 / SMALL of a unit shares units with others.
SMALL = 4
#: Bits of a filter at most: 2^20 words, which bounds its broadcast.
FILTER_BITS = 1 << 26


class Tables:
    """Intermediate tables in the shared folder, deleted together."""

    def __init__(self, tag: str):
        self.tag, self.paths = tag, []

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        out, path = common.stored(df, f"{self.tag}-{name}")
        self.paths.append(path)
        return out

    def keep_with(self, df: DataFrame, name: str, **totals: Column) -> tuple[DataFrame, dict[str, int]]:
        """The stored frame and sums over it (0 for an empty one), made while it is written."""
        seen = Observation()
        out = self.keep(df.observe(seen, *[F.sum(c).alias(k) for k, c in totals.items()]), name)
        return out, {k: seen.get[k] or 0 for k in totals}

    def drop(self, df: DataFrame) -> None:
        common.remove(df.sparkSession, *self.paths)
        self.paths = []


def sifted(rows: DataFrame, key: str, wanted: DataFrame, n: int) -> tuple[DataFrame, DataFrame | None]:
    """The rows whose ``key`` may be among the ``n`` values of ``wanted`` (column ``key`` of it), and the others.

    A bitmap of hashed keys, broadcast as at most FILTER_BITS / 64 rows, spares what an exact join
    after it would shuffle. Beyond half a bit a key it would hold back little: all rows may then.
    """
    bits = 1 << 12
    while bits < 8 * n and bits < FILTER_BITS:
        bits *= 2
    if 2 * bits < n:
        return rows, None
    place = F.pmod(F.xxhash64(key), F.lit(bits))
    words = wanted.select(place.alias("__at")).select(F.shiftright("__at", 6).alias("__word"), F.expr("shiftleft(1L, cast(__at & 63 as int))").alias("__bit"))
    words = words.groupBy("__word").agg(F.bit_or("__bit").alias("__bits"))
    near = rows.withColumn("__at", place).withColumn("__word", F.shiftright("__at", 6)).join(F.broadcast(words), "__word", "left")
    found = "coalesce(__bits, 0L) & shiftleft(1L, cast(__at & 63 as int))"
    return near.where(f"({found}) <> 0").select(*rows.columns), near.where(f"({found}) = 0").select(*rows.columns)


def thinned(rows: DataFrame, key: str, wanted: DataFrame, n: int) -> DataFrame:
    """The first of what ``sifted`` gives."""
    return sifted(rows, key, wanted, n)[0]


def components(links: DataFrame, tables: Tables) -> DataFrame:
    """(key, part): the smallest key reachable over links (a, b), for the keys that have a link."""
    both = tables.keep(links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "graph")
    part = both.groupBy(F.col("a").alias("key")).agg(F.min("b").alias("b")).select("key", F.least("key", "b").alias("part"))
    part = tables.keep(part, "part")
    while True:
        near = both.join(part, both["b"] == part["key"]).groupBy(F.col("a").alias("key")).agg(F.min("part").alias("near"))
        best = part.join(near, "key").select("key", "part", F.least("part", "near").alias("best"))
        jump = part.select(F.col("key").alias("best"), F.col("part").alias("far"))
        low = F.least("best", "far")
        after = best.join(jump, "best").select("key", low.alias("part"), (low < F.col("part")).cast("long").alias("moved"))
        part, total = tables.keep_with(after, "part", moved=F.col("moved"))
        part = part.select("key", "part")
        if not total["moved"]:
            return part


def _blocks(keys: str, size: str, most_keys: int, most_size: int) -> Column:
    return F.ceil(F.greatest(F.lit(1.0), F.col(keys) / most_keys, F.col(size) / most_size)).cast("long")


def _pools(keys: int, size: int, most_keys: int, most_size: int) -> int:
    return max(1, -(-keys // most_keys), -(-size // most_size))


def _pool(name: str, pools: int) -> Column:
    return F.xxhash64(F.lit("pool"), F.pmod(F.xxhash64(name), F.lit(pools)))


def first_units(live: DataFrame, hubs: DataFrame, tables: Tables, most_keys: int, most_size: int) -> tuple[DataFrame, DataFrame]:
    """(unit, key, part = key, was = key): each key with others of its home, from rows (band, key, n); and (key, was), its unit."""
    met = live.join(hubs, "band").groupBy("key", "hub").agg(F.count("*").alias("c"), F.min("n").alias("n"))
    most = F.max(F.struct("c", F.bitwise_not("hub").alias("least")))  # not reverses the order
    homes = met.groupBy("key").agg(most.alias("m"), F.min("n").alias("n")).select("key", F.bitwise_not("m.least").alias("home"), "n")
    homes = tables.keep(homes, "homes")
    few = f"c * {SMALL} < {most_keys} and s * {SMALL} < {most_size}"
    sized = homes.groupBy("home").agg(F.count("*").alias("c"), F.sum("n").alias("s")).withColumn("few", F.expr(few))
    sized, total = tables.keep_with(sized, "sizes", c=F.expr("if(few, c, 0)"), s=F.expr("if(few, s, 0)"))
    pooled, blocks = _pool("home", _pools(total["c"], total["s"], most_keys, most_size)), _blocks("c", "s", most_keys, most_size)
    unit = F.when(F.col("few"), pooled).otherwise(F.xxhash64("home", F.pmod(F.xxhash64("key"), blocks)))
    own = tables.keep(homes.join(sized, "home").select(unit.alias("unit"), "key"), "own")
    starts = sized.where("not few").select("home", F.explode(F.sequence(F.lit(0).cast("long"), blocks - 1)).alias("block"))
    rows = own.union(starts.select(F.xxhash64("home", "block"), "home")).distinct()
    return rows.select("unit", "key", F.col("key").alias("part"), F.col("key").alias("was")), own.select("key", F.col("unit").alias("was"))


def later_units(live: DataFrame, hubs: DataFrame, was: DataFrame, tables: Tables, most_keys: int, most_size: int) -> DataFrame:
    """(unit, key, part, was) of blocks that share a bucket and don't lie in one part, from rows (band, key, n, part), (band, hub) and (key, was)."""
    near = live.join(hubs, "band").groupBy("key").agg(F.min("hub").alias("home"))
    wider = live.join(near, "key").groupBy("band").agg(F.min("home").alias("hub"))
    homes = tables.keep(live.join(wider, "band").groupBy("key", "part").agg(F.min("hub").alias("home"), F.min("n").alias("n")), "cells")
    seen = live.select("band", "key").join(homes, "key").groupBy("band", "home").agg(F.min("part").alias("lo"), F.max("part").alias("hi"))
    seen = tables.keep(seen, "seen")
    apart = "not (x.lo = x.hi and y.lo = y.hi and x.lo = y.lo)"
    met = seen.alias("x").join(seen.alias("y"), F.expr(f"x.band = y.band and x.home <= y.home and {apart}"))
    met = met.select(F.col("x.home").alias("i"), F.col("y.home").alias("j")).distinct()

    many = f"2 * c >= {most_keys} or 2 * s >= {most_size}"
    sized = homes.groupBy("home", "part").agg(F.count("*").alias("c"), F.sum("n").alias("s")).withColumn("many", F.expr(many))
    sized = tables.keep(sized, "part-sizes")
    mixed = sized.where("not many").groupBy("home").agg(F.sum("c").alias("c"), F.sum("s").alias("s"))
    mixed = mixed.select("home", _blocks("c", "s", most_keys, most_size).alias("mixed"))
    sized = sized.select("home", "part", "many", _blocks("c", "s", most_keys, most_size).alias("own")).join(mixed, "home", "left")
    block = F.when(F.col("many"), F.xxhash64("part", F.pmod(F.xxhash64("key"), F.col("own")))).otherwise(F.pmod(F.xxhash64("part"), F.col("mixed")))
    members = homes.join(sized, ["home", "part"]).select("home", block.alias("block"), "key", "part", "n")
    members = tables.keep(members.join(was, "key"), "members")

    blocks = members.groupBy("home", "block").agg(F.min("part").alias("lo"), F.max("part").alias("hi"), F.count("*").alias("c"), F.sum("n").alias("s"))
    blocks = tables.keep(blocks, "blocks")
    x, y = blocks.alias("x"), blocks.alias("y")
    pairs = met.join(x, F.expr("i = x.home")).join(y, F.expr(f"j = y.home and (i < j or x.block <= y.block) and {apart}"))
    pairs = pairs.select("i", F.col("x.block").alias("p"), "j", F.col("y.block").alias("q"), F.expr("x.c + y.c").alias("c"), F.expr("x.s + y.s").alias("s"))
    few = f"c * {SMALL} < 2 * {most_keys} and s * {SMALL} < 2 * {most_size}"
    pairs, total = tables.keep_with(pairs.withColumn("few", F.expr(few)), "pairs", c=F.expr("if(few, c, 0)"), s=F.expr("if(few, s, 0)"))
    unit = F.when(F.col("few"), _pool("i", _pools(total["c"], total["s"], 2 * most_keys, 2 * most_size))).otherwise(F.xxhash64("i", "p", "j", "q"))
    ends = F.array(F.struct(F.col("i").alias("home"), F.col("p").alias("block")), F.struct(F.col("j").alias("home"), F.col("q").alias("block")))
    units = pairs.select(unit.alias("unit"), F.explode(ends).alias("end")).select("unit", "end.*").distinct()
    return units.join(members, ["home", "block"]).select("unit", "key", "part", "was").distinct()


def classes(buckets: DataFrame, unit_links: Callable[[DataFrame], DataFrame], tables: Tables, most_keys: int, most_size: int) -> DataFrame | None:
    """(key, part) of the keys with a link; None without buckets.

    ``buckets``: (band, key, n), each key once in a band, bands of one key left out. ``unit_links`` gives links (a, b) that join
    all that is linked among the keys of each unit, from rows (unit, key, part, was); keys of one part
    or of one ``was`` need not be compared again. A unit holds about ``2 * most_keys`` keys whose n
    sum to ``2 * most_size``; one key may be larger.
    """
    hubs, some = tables.keep_with(buckets.groupBy("band").agg(F.min("key").alias("hub")), "hubs", rows=F.lit(1))
    if not some["rows"]:
        return None
    rows, was = first_units(buckets, hubs, tables, most_keys, most_size)
    part = components(unit_links(rows), tables)
    parted = tables.keep(buckets.join(part, "key", "left").select("band", "key", "n", F.coalesce("part", "key").alias("part")), "parted")
    open_ = tables.keep(parted.groupBy("band").agg(F.min("part").alias("lo"), F.max("part").alias("hi")).where("lo < hi").select("band"), "open")
    left, some = tables.keep_with(parted.join(open_, "band", "left_semi"), "left", rows=F.lit(1))
    if not some["rows"]:
        return part
    links = unit_links(later_units(left, hubs, was, tables, most_keys, most_size))
    return components(part.select(F.col("part").alias("a"), F.col("key").alias("b")).where("a <> b").union(links), tables)
