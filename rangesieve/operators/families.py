"""More filter families: prefix search over hash codes, piecewise hashing, and leaves whose width follows the queries. As in
`filters`, a range with a key is never answered "empty", and null, reversed, repeated or clashing input has the same answers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangesieve.functions.hashing import SPARK, HashParams, with_draws
from rangesieve.operators.filters import MOST, level_bits, level_descent, lhf_pieces, ttf_probe
from rangesieve.operators.order import answered, grows, predecessor, questions

# --- prefix search ----------------------------------------------------------------------------------------------------


def prefix_table(codes: DataFrame, top: int) -> DataFrame:
    """(level, node, least, greatest): the extreme codes below every prefix at levels 0..top."""
    levels = codes.select("z", F.explode(F.sequence(F.lit(0), F.lit(top))).alias("level"))
    return levels.selectExpr("level", "shiftright(z, level) AS node", "z").groupBy("level", "node").agg(F.min("z").alias("least"), F.max("z").alias("greatest"))


def psh_probe(codes: DataFrame, ranges: DataFrame, p: HashParams) -> DataFrame:
    """The locality-hash filter searched by prefixes: at the fork of a piece's ends, the left child must reach up to
    the lower end or the right child down to the upper one. Equality joins only; the answers are those of lhf_probe."""
    pieces = lhf_pieces(questions(ranges), p).withColumn("d", F.expr(f"{SPARK.bit_length('lo ^ hi')}"))
    below = F.expr("CAST(greatest(d - 1, 0) AS INT)")
    sides = pieces.select("q", "lo", "hi", below.alias("level")).select(
        "q", "lo", "hi", "level", F.inline(F.array(F.struct(F.lit(True).alias("is_left"), F.expr("shiftright(lo, level)").alias("node")), F.struct(F.lit(False).alias("is_left"), F.expr("shiftright(hi, level)").alias("node"))))
    )
    table = prefix_table(codes, max(1, (p.r - 1).bit_length())).selectExpr("level AS l_", "node AS n_", "least", "greatest")
    met = sides.join(grows(table), (F.col("level") == F.col("l_")) & (F.col("node") == F.col("n_")))
    single = (F.col("lo") == F.col("hi")) & (F.col("least") == F.col("lo"))
    hit = F.when(F.col("lo") == F.col("hi"), single).when(F.col("is_left"), F.col("greatest") >= F.col("lo")).otherwise(F.col("least") <= F.col("hi"))
    return answered(ranges, met.select("q", hit.alias("hit")))


# --- piecewise hashing ------------------------------------------------------------------------------------------------


def _phb_placed(nodes: DataFrame, delta: int, words: int) -> DataFrame:
    """Add the place of node v of a layer: its upper bits choose a word by hash, its low bits keep their order in the word."""
    drawn = with_draws(nodes, [("_d", f"shiftright(v, {delta}) * 64 + layer", words, 400)])
    return drawn.select(*nodes.columns, F.expr(f"_d * {2**delta} + (v & {2**delta - 1})").alias("place"))


def phb_bits(keys: DataFrame, layers: int, delta: int, words: int) -> DataFrame:
    nodes = keys.where("k is not null").select("k", F.explode(F.sequence(F.lit(0), F.lit(layers - 1))).alias("layer")).selectExpr("layer", f"shiftright(k, layer * {delta}) AS v").distinct()
    return _phb_placed(nodes, delta, words).select("place").distinct()


def phb_cover(asked: DataFrame, layers: int, delta: int) -> DataFrame:
    """(q, layer, v): the least nodes of the layers that make up a range; at the top layer all nodes inside."""
    at = asked.select("q", "a", "b", F.explode(F.sequence(F.lit(0), F.lit(layers - 1))).alias("layer"))
    ends = at.selectExpr("q", "layer", f"shiftright(a + shiftleft(1L, layer * {delta}) - 1, layer * {delta}) AS x", f"shiftright(b + 1, layer * {delta}) - 1 AS y", f"shiftleft(shiftright(a + shiftleft(1L, (layer + 1) * {delta}) - 1, (layer + 1) * {delta}), {delta}) AS x2", f"shiftleft(shiftright(b + 1, (layer + 1) * {delta}), {delta}) - 1 AS y2").where("x <= y")
    nodes = F.when((F.col("layer") == layers - 1) | (F.col("x2") > F.col("y2")), F.expr("sequence(x, y)")).otherwise(F.expr("concat(if(x < x2, sequence(x, x2 - 1), array()), if(y > y2, sequence(y2 + 1, y), array()))"))
    return ends.select("q", "layer", F.explode(nodes).alias("v"))


def phb_probe(bits_set: DataFrame, ranges: DataFrame, layers: int, delta: int, words: int, most: int = MOST) -> DataFrame:
    """A node counts if its bit and those of its ancestors in all layers above are set; a range with more than `most`
    nodes at the top layer is answered maybe, as such a filter must bound its probes."""
    top, asked = (layers - 1) * delta, questions(ranges)
    wide = asked.where(f"shiftright(b, {top}) - shiftright(a, {top}) >= {most}").select("q", F.lit(True).alias("hit"))
    cover = phb_cover(asked.where(f"shiftright(b, {top}) - shiftright(a, {top}) < {most}"), layers, delta)
    path = cover.selectExpr("q", "layer AS from_layer", "v AS from_v", f"explode(sequence(layer, {layers - 1})) AS layer").selectExpr("q", "from_layer", "from_v", "layer", f"shiftright(from_v, (layer - from_layer) * {delta}) AS v")
    met = _phb_placed(path, delta, words).join(grows(bits_set.withColumnRenamed("place", "_p")), F.col("place") == F.col("_p"))
    full = met.groupBy("q", "from_layer", "from_v").agg(F.count("*").alias("_n")).where(F.col("_n") == layers - F.col("from_layer"))
    return answered(ranges, full.select("q", F.lit(True).alias("hit")).union(wide))


# --- leaves whose width follows the queries ---------------------------------------------------------------------------


def region_leaves(keys: DataFrame, regions: DataFrame, region_shift: int, cold: int) -> DataFrame:
    """(z, hi): occupied dyadic leaves; of width 2^s inside a region of `regions` (region, s), of width 2^cold
    elsewhere. Widths never pass that of a region, so leaves don't overlap."""
    placed = keys.select("k", F.expr(f"shiftright(k, {region_shift})").alias("_r")).join(regions.selectExpr("region", f"CAST(least(s, {region_shift}) AS INT) AS s"), F.col("_r") == F.col("region"), "left")
    cut = placed.select("k", F.coalesce("s", F.lit(min(cold, region_shift))).alias("s"))
    return cut.selectExpr("shiftleft(shiftright(k, s), s) AS z", "shiftleft(shiftright(k, s), s) + shiftleft(1L, s) - 1 AS hi").distinct()


leaves_probe = ttf_probe
__all__ = ["adapted_regions", "leaves_probe", "level_bits", "level_descent", "phb_bits", "phb_probe", "psh_probe", "region_leaves", "sample_gaps", "weighted_regions"]


def sample_gaps(keys: DataFrame, empty: DataFrame, n: int | None = None) -> DataFrame:
    """Empty ranges with `level`: the least dyadic level at which a block of an end also holds a key. Filters that
    keep prefixes at or above that level must answer maybe. One predecessor and one successor join serve all levels."""
    z = keys.select(F.col("k").alias("z"))
    before = predecessor(z, empty, "a", n=n).select(*empty.columns, F.col("pred.z").alias("_before"))
    mirrored = keys.select((-F.col("k")).alias("z"))
    both = predecessor(mirrored, before.withColumn("_m", -F.col("b")), "_m", n=n).select(*before.columns, (-F.col("pred.z")).alias("_after"))
    level = F.least(F.coalesce(F.expr(SPARK.bit_length("a ^ _before")), F.lit(63)), F.coalesce(F.expr(SPARK.bit_length("b ^ _after")), F.lit(63)))
    return both.select(*empty.columns, level.cast("int").alias("level"))


def adapted_regions(keys: DataFrame, seen: DataFrame, coarse: int) -> DataFrame:
    """(region, s) for the buckets of width 2^coarse in which an observed empty range was a false positive: split them
    until the range is told apart."""
    wrong = sample_gaps(keys, seen).where(F.col("level") <= coarse)
    ends = wrong.select("level", F.explode(F.array(F.expr(f"shiftright(a, {coarse})"), F.expr(f"shiftright(b, {coarse})"))).alias("region"))
    return ends.groupBy("region").agg(F.greatest(F.min("level") - 1, F.lit(0)).alias("s"))


def weighted_regions(seen: DataFrame, region_shift: int, hot: int) -> DataFrame:
    """(region, s): regions that get at least the mean number of the sample's queries have narrow buckets of 2^hot."""
    mass = seen.groupBy(F.expr(f"shiftright(a, {region_shift})").alias("region")).agg(F.count("*").alias("c"))
    mean = mass.agg(F.avg("c").alias("_mean"))
    return mass.join(F.broadcast(mean), F.col("c") >= F.col("_mean")).select("region", F.lit(hot).alias("s"))
