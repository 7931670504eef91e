"""The filters. Each keeps a set of codes and maps a range to pieces of code space; most then ask one question: does
any code lie in a piece? A filter may answer "maybe" for an empty range, never "empty" for one with a key.

Ranges are frames with the columns a and b and any others. All rows and columns come back with `maybe`, which is null
where an end is null or a > b. Ends that repeat are asked once; ids may repeat or be null, names may clash, frames may
be empty (without keys every answer is false). Keys and ends are integers from -2^62 to 2^62 - 1; null keys never enter,
and keys may repeat. Between `questions` and `answered` a question is known by q = (a, b).
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangesieve.functions.hashing import SPARK, HashParams, local_hash_fast, with_draws, with_local_hash
from rangesieve.operators.order import answered, any_code_in, grows, predecessor, questions, rank


# --- the bounded filter -----------------------------------------------------------------------------------------------


def lhf_codes(keys: DataFrame, p: HashParams, distinct: bool = True) -> DataFrame:
    """Codes z; a probe takes them with their repeats, so that they needn't be shuffled twice."""
    codes = with_local_hash(keys.where("k is not null").select("k"), [("z", "k")], p).select("z")
    return codes.distinct() if distinct else codes


def lhf_pieces(asked: DataFrame, p: HashParams, hashed=None) -> DataFrame:
    """(q, lo, hi) in code space. A range over one block border is split at it; one that wraps inside the code space
    gives two pieces; one that covers a whole block gives the whole space."""
    r = p.r
    hashed = hashed or (lambda df: with_local_hash(df, [("x", "a"), ("y", "b")], p))
    edge = f"(b - {SPARK.floor_mod('b', r)})"
    split = asked.select("q", "a", "b", F.expr(f"{SPARK.floor_div('b', r)} - {SPARK.floor_div('a', r)}").alias("cross"))
    halves = f"if(cross = 0, array(struct(a, b, false AS whole)), if(cross = 1, array(struct(a, {edge} - 1 AS b, false AS whole), struct({edge} AS a, b, false AS whole)), array(struct(a, b, true AS whole))))"
    ends = hashed(split.select("q", F.inline(F.expr(halves))))
    parts = f"if(whole, array(struct(0L AS lo, {r - 1}L AS hi)), if(x <= y, array(struct(x AS lo, y AS hi)), array(struct(0L AS lo, y AS hi), struct(x AS lo, {r - 1}L AS hi))))"
    return ends.select("q", F.inline(F.expr(parts)))


def lhf_probe(codes: DataFrame, ranges: DataFrame, p: HashParams) -> DataFrame:
    return answered(ranges, lhf_hits(codes, questions(ranges), p))


def lhf_hits(codes: DataFrame, asked: DataFrame, p: HashParams) -> DataFrame:
    return any_code_in(codes, lhf_pieces(asked, p), p.n or None)


def lhf_probe_fast(keys: DataFrame, ranges: DataFrame, p: HashParams) -> DataFrame:
    """The filter with a practical hash of the block."""
    codes = keys.where("k is not null").select(F.expr(local_hash_fast("k", p)).alias("z"))
    hashed = lambda df: df.selectExpr("*", f"{local_hash_fast('a', p)} AS x", f"{local_hash_fast('b', p)} AS y")
    return answered(ranges, any_code_in(codes, lhf_pieces(questions(ranges), p, hashed), p.n or None))


def lhf_count(codes: DataFrame, ranges: DataFrame, p: HashParams) -> DataFrame:
    """Ranges with est: codes (distinct) in the range's pieces, from differences of ranks (whole blocks count all codes);
    null where an end is null or the ends are reversed."""
    from rangesieve.operators.order import count_codes_upto

    # Both ends of a piece in one pass, as points that add and take away.
    ends = lhf_pieces(questions(ranges), p).select("q", F.inline(F.expr("array(struct(hi AS x, 1L AS sign), struct(lo - 1 AS x, -1L AS sign))")))
    est = count_codes_upto(codes, ends, "x", "upto", p.n or None).groupBy("q").agg(F.sum(F.col("sign") * F.col("upto")).alias("est")).select(F.col("q.a").alias("x_"), F.col("q.b").alias("y_"), "est")
    return ranges.join(grows(est), (F.col("a") == F.col("x_")) & (F.col("b") == F.col("y_")), "left").select(*ranges.columns, "est")


def correct_count(counts: DataFrame, p: HashParams) -> DataFrame:
    """Expected number of keys behind a count of codes. Blocks elsewhere leave n * length / r codes in the range, and a
    code stands for (n - 1) / 2r keys more than one, as keys that meet another's code add none: both are taken back."""
    foreign = F.lit(float(p.n)) * (F.col("b") - F.col("a") + 1) / F.lit(float(p.r))
    return counts.withColumn("corrected", F.greatest(F.lit(0.0), F.col("est") * F.lit(1 + max(p.n - 1, 0) / (2.0 * p.r)) - foreign))


def lhf_merge(one: DataFrame, two: DataFrame) -> DataFrame:
    """Codes of the union of two key sets under the same parameters."""
    return one.union(two).distinct()


# --- buckets ----------------------------------------------------------------------------------------------------------


def cbf_codes(keys: DataFrame, s: int, distinct: bool = True) -> DataFrame:
    codes = keys.where("k is not null").select(F.expr(f"k div {s}").alias("z"))
    return codes.distinct() if distinct else codes


def cbf_probe(codes: DataFrame, ranges: DataFrame, s: int, n: int | None = None) -> DataFrame:
    return answered(ranges, cbf_hits(codes, questions(ranges), s, n))


def cbf_hits(codes: DataFrame, asked: DataFrame, s: int, n: int | None = None) -> DataFrame:
    return any_code_in(codes, asked.select("q", F.expr(f"a div {s}").alias("lo"), F.expr(f"b div {s}").alias("hi")), n)


def neighbours(keys: DataFrame, n: int | None = None) -> DataFrame:
    """k with prev and next key (null at the ends), by a predecessor join on ranks."""
    ranked = rank(keys, "k", n=n)
    p = ranked.select(F.col("k").alias("prev"), (F.col("i") + 1).alias("_p"))
    n = ranked.select(F.col("k").alias("next"), (F.col("i") - 1).alias("_n"))
    return ranked.join(grows(p), F.col("i") == F.col("_p"), "left").join(grows(n), F.col("i") == F.col("_n"), "left").select("k", "i", "prev", "next")


def cbf_ones_by_width(keys: DataFrame) -> DataFrame:
    """(j, t): occupied buckets of width 2^j for every j, from one histogram of the highest bit in which sorted
    neighbours differ: a bucket border lies between two neighbours iff they differ at bit j or above."""
    top = neighbours(keys).where("prev is not null").select(F.expr(SPARK.bit_length("k ^ prev")).alias("bits")).groupBy("bits").agg(F.count("*").alias("c"))
    some = keys.agg((F.count("*") > 0).cast("long").alias("some"))
    js = keys.sparkSession.range(63).select(F.col("id").cast("int").alias("j"))
    return js.join(F.broadcast(top), F.col("bits") > F.col("j"), "left").groupBy("j").agg(F.coalesce(F.sum("c"), F.lit(0)).alias("c")).join(F.broadcast(some)).select("j", (F.col("c") + F.col("some")).cast("long").alias("t"))


#: (bits in which a key parts from the one before, from the one after): how many keys; 64 where there is none.
Parted = dict[tuple[int, int], int]


def parted(keys: DataFrame, n: int | None = None) -> Parted:
    """One pass over the sorted keys for all sizes that follow them: at most 64 * 64 rows."""
    bits = [F.coalesce(F.expr(SPARK.bit_length(f"k ^ {x}")), F.lit(64)).alias(x) for x in ("prev", "next")]
    return {(r[0], r[1]): r[2] for r in neighbours(keys, n).select(*bits).groupBy("prev", "next").agg(F.count("*")).collect()}


def ones_of(found: Parted) -> dict[int, int]:
    """`cbf_ones_by_width` from where keys part (a key without one before it opens a bucket, too)."""
    return {j: sum(c for (p, _), c in found.items() if p > j) for j in range(63)}


def inner_nodes_of(found: Parted, w: int) -> int:
    """`ttf_inner_nodes` from where keys part."""
    ones = ones_of(found)
    return sum(ones[j] - sum(c for pair, c in found.items() if min(pair) > j) for j in range(1, w + 1))


def cbf_choose(keys: DataFrame, bits: float, u: int) -> int:
    """The least width 2^j whose space stays within the budget."""
    from rangesieve.functions.models import space_bucket

    found = {r.j: r.t for r in cbf_ones_by_width(keys).collect()}  # 63 rows
    n = found[0]
    fits = [j for j, t in found.items() if t and 2**j <= u and space_bucket(t, u, 2**j) <= bits * n]
    return 2 ** min(fits) if fits else u


# --- tries and learned maps -------------------------------------------------------------------------------------------


def ttf_leaves(keys: DataFrame, suffix_bits: int = 0) -> DataFrame:
    """(z, hi, k): dyadic interval of each key's distinguishing prefix and suffix_bits real bits more."""
    far = F.least(F.coalesce(F.expr(SPARK.bit_length("k ^ prev")), F.lit(64)), F.coalesce(F.expr(SPARK.bit_length("k ^ next")), F.lit(64)))
    shift = F.greatest(F.least(far - 1, F.lit(62)) - suffix_bits, F.lit(0)).cast("int")
    cut = neighbours(keys).withColumn("s", shift)
    return cut.select(F.expr("shiftleft(shiftright(k, s), s)").alias("z"), F.expr("shiftleft(shiftright(k, s), s) + shiftleft(1L, s) - 1").alias("hi"), "k", "s")


def ttf_inner_nodes(keys: DataFrame, w: int) -> int:
    """Distinct prefixes that hold two keys or more, over all levels: occupied ones less those of a single key, from
    two histograms of the highest bit in which neighbours differ."""
    alone = F.least(F.coalesce(F.expr(SPARK.bit_length("k ^ prev")), F.lit(64)), F.coalesce(F.expr(SPARK.bit_length("k ^ next")), F.lit(64)))
    far = {r.far: r.c for r in neighbours(keys).groupBy(alone.alias("far")).agg(F.count("*").alias("c")).collect()}  # 65 rows
    ones = {r.j: r.t for r in cbf_ones_by_width(keys).collect()}  # 63 rows
    return sum(ones[j] - sum(c for d, c in far.items() if d > j) for j in range(1, w + 1))


def ttf_probe(leaves: DataFrame, ranges: DataFrame, n: int | None = None) -> DataFrame:
    return answered(ranges, ttf_hits(leaves, questions(ranges), n))


def ttf_hits(leaves: DataFrame, asked: DataFrame, n: int | None = None) -> DataFrame:
    found = predecessor(leaves.select("z", F.col("hi").alias("end")), asked, "b", ["end"], n)
    return found.select("q", (F.col("pred.end") >= F.col("a")).alias("hit"))


def ttf_probe_points(leaves: DataFrame, ranges: DataFrame, hash_bits: int, n: int | None = None) -> DataFrame:
    """Point batches with hashed suffixes: the point must lie in a leaf and share the hash of the leaf's key. A range of
    more than a point is asked by its leaves alone."""
    tagged = with_draws(leaves, [("tag", "k", 2**hash_bits, 77)]).select("z", F.col("hi").alias("end"), "tag")
    found = predecessor(tagged, with_draws(questions(ranges), [("mine", "a", 2**hash_bits, 77)]), "b", ["end", "tag"], n)
    hit = (F.col("pred.end") >= F.col("a")) & ((F.col("a") < F.col("b")) | (F.col("pred.tag") == F.col("mine")))
    return answered(ranges, found.select("q", hit.alias("hit")))


def lbf_knots(keys: DataFrame, every: int) -> DataFrame:
    """(z, i, next): every `every`-th key with its number and the following knot."""
    ranked = rank(keys, "k").where(f"(i - 1) % {every} = 0").select(F.col("k").alias("z"), F.expr(f"(i - 1) div {every}").alias("i"))
    follow = ranked.select(F.col("z").alias("next"), (F.col("i") - 1).alias("_i"))
    return ranked.join(grows(follow), F.col("i") == F.col("_i"), "left").drop("_i")


def lbf_map(knots: DataFrame, points: DataFrame, at: str, name: str, every: int, k: int) -> DataFrame:
    """Monotone integer map of a value through the knots' piecewise linear ranks; below all knots -1."""
    found = predecessor(knots, points, at, ["i", "next"])
    step = F.expr(f"CAST((CAST({at} - pred.z AS DECIMAL(38,0)) * {every * k}) div CAST(coalesce(pred.next, pred.z + {2**40}) - pred.z AS DECIMAL(38,0)) AS BIGINT)")
    value = F.when(F.col("pred").isNull(), F.lit(-1).cast("long")).otherwise(F.col("pred.i") * every * k + step)
    return found.select(*points.columns, value.alias(name))


def lbf_codes(keys: DataFrame, knots: DataFrame, every: int, k: int) -> DataFrame:
    return lbf_map(knots, keys, "k", "z", every, k).select("z").distinct()


def lbf_probe(codes: DataFrame, knots: DataFrame, ranges: DataFrame, every: int, k: int, n: int | None = None) -> DataFrame:
    return answered(ranges, lbf_hits(codes, knots, questions(ranges), every, k, n))


def lbf_hits(codes: DataFrame, knots: DataFrame, asked: DataFrame, every: int, k: int, n: int | None = None) -> DataFrame:
    """Both ends go through the map in one pass, as points of one frame."""
    ends = asked.select("q", F.inline(F.expr("array(struct(a AS x), struct(b AS x))"))).distinct()
    mapped = lbf_map(knots, ends, "x", "z", every, k).groupBy("q").agg(F.min("z").alias("lo"), F.max("z").alias("hi"))
    return any_code_in(codes, mapped, n)


#: What a per-level filter hashes for a node: its level and its lowest 58 bits, so that no key is too large (up to 16 levels).
LEVEL_NODE = f"(({{node}}) & {2**58 - 1}) * 16 + {{level}}"
#: Prefixes of a Bloom filter that one question may ask.
MOST = 4_096

# --- Bloom families ---------------------------------------------------------------------------------------------------


def bloom_places(df: DataFrame, value: str, bits: int, hashes: int, stream: int = 0) -> DataFrame:
    """Each row once per hash function: columns j, place."""
    drawn = with_draws(df, [(f"_d{j}", value, bits, 100 + stream * 16 + j) for j in range(hashes)])
    places = F.array(*[F.struct(F.lit(j).alias("j"), F.col(f"_d{j}").alias("place")) for j in range(hashes)])
    return drawn.select(*df.columns, F.inline(places))


def bloom_bits(df: DataFrame, value: str, bits: int, hashes: int, stream: int = 0) -> DataFrame:
    return bloom_places(df.select(value).distinct(), value, bits, hashes, stream).select("place").distinct()


def bloom_members(df: DataFrame, value: str, bloom: DataFrame, bits: int, hashes: int, stream: int = 0) -> DataFrame:
    """Rows of df (distinct) whose places are all set."""
    asked = bloom_places(df, value, bits, hashes, stream)
    if hashes == 1:  # one place a row: nothing to count, so one shuffle
        return asked.join(grows(bloom), "place", "left_semi").select(*df.columns)
    hit = asked.join(grows(bloom.withColumnRenamed("place", "_p")), F.col("place") == F.col("_p"))
    return hit.groupBy(*df.columns).agg(F.count("*").alias("_n")).where(F.col("_n") == hashes).drop("_n")


def pointwise_probe(keys: DataFrame, ranges: DataFrame, bits: int, hashes: int) -> DataFrame:
    """Ask a point filter for every point of the range."""
    bloom = bloom_bits(keys, "k", bits, hashes)
    points = questions(ranges).select("q", F.explode(F.expr("sequence(a, b)")).alias("x"))
    return answered(ranges, bloom_members(points, "x", bloom, bits, hashes).select("q", F.lit(True).alias("hit")))


def dyadic_cover(asked: DataFrame, top: int, low: int = 0, q: str = "q") -> DataFrame:
    """(q, level, node): canonical dyadic nodes of [a, b] at levels low..top; at the top all nodes inside."""
    levels = asked.select(q, "a", "b", F.explode(F.sequence(F.lit(low), F.lit(top))).alias("level"))
    ends = levels.selectExpr(q, "level", "a", "b", "shiftright(a + shiftleft(1L, level) - 1, level) AS x", "shiftright(b + 1, level) - 1 AS y").where("x <= y")
    nodes = F.when(F.col("level") == top, F.expr("sequence(x, y)")).otherwise(F.expr("array_distinct(concat(if(x & 1 = 1 or x = y, array(x), array()), if(y & 1 = 0 or x = y, array(y), array())))"))
    return ends.select(q, "level", F.explode(nodes).alias("node"))


def plb_bits(keys: DataFrame, top: int, bits: int, hashes: int) -> DataFrame:
    """place of the prefixes at levels 0..top."""
    return level_bits(keys, [hashes] * (top + 1), bits)


def plb_probe(bits_set: DataFrame, ranges: DataFrame, top: int, bits: int, hashes: int) -> DataFrame:
    return level_descent(bits_set, ranges, [hashes] * (top + 1), bits)[0]


def level_bits(keys: DataFrame, hashes: list[int], bits: int) -> DataFrame:
    """Bloom places of the prefixes at level i, with hashes[i] functions there (few above, many at the leaves). Equal
    places are dropped once, at the end: prefixes that repeat set the same ones."""
    most = max(hashes)
    nodes = keys.where("k is not null").select("k", F.posexplode(F.array(*[F.lit(c) for c in hashes])).alias("level", "c")).selectExpr("c", f"{LEVEL_NODE.format(node='shiftright(k, level)', level='level')} AS v")
    drawn = with_draws(nodes, [(f"_d{j}", "v", bits, 132 + j) for j in range(most)])
    return drawn.select(F.explode(F.slice(F.array(*[F.col(f"_d{j}") for j in range(most)]), F.lit(1), F.col("c"))).alias("place")).distinct()


def level_descent(bits_set: DataFrame, ranges: DataFrame, hashes: list[int], bits: int) -> tuple[DataFrame, Callable[[], DataFrame]]:
    """(answers, work): work() has (level, nodes, places) asked on the way down."""
    hits, work = level_walk(bits_set, questions(ranges), hashes, bits)
    return answered(ranges, hits), work


def level_walk(bits_set: DataFrame, asked: DataFrame, hashes: list[int], bits: int) -> tuple[DataFrame, Callable[[], DataFrame]]:
    """(hits, work): walk down from the dyadic cover; a node lives on if its own bits are set; a leaf that lives means
    maybe. Nodes of a question are disjoint, so none repeats."""
    top = len(hashes) - 1
    cover, alive, walked = dyadic_cover(asked, top), None, []
    for level in range(top, -1, -1):
        nodes = cover.where(F.col("level") == level).select("q", "node")
        if alive is not None:
            nodes = nodes.union(alive.select("q", F.explode(F.expr("array(node * 2, node * 2 + 1)")).alias("node")))
        asked = nodes.selectExpr("q", "node", f"{LEVEL_NODE.format(node='node', level=level)} AS v")
        walked.append((level, asked))
        alive = bloom_members(asked, "v", bits_set, bits, hashes[level], 2).select("q", "node")

    def work() -> DataFrame:
        done = [asked.agg(F.lit(level).alias("level"), F.count("*").alias("nodes"), (F.count("*") * hashes[level]).alias("places")) for level, asked in walked]
        return reduce(DataFrame.union, done)

    return alive.select("q", F.lit(True).alias("hit")), work


def tpb_probe(keys: DataFrame, ranges: DataFrame, shift1: int, shift2: int, bits: int, hashes: int, most: int = MOST) -> DataFrame:
    """Exact prefixes above shift1 and a Bloom filter of the prefixes above shift2 < shift1. A question may ask `most`
    prefixes of the Bloom filter; a wider range is answered maybe, as such a filter must bound its probes."""
    return answered(ranges, tpb_hits(keys, questions(ranges), shift1, shift2, bits, hashes, most))


def tpb_hits(keys: DataFrame, asked: DataFrame, shift1: int, shift2: int, bits: int, hashes: int, most: int = MOST) -> DataFrame:
    some = keys.where("k is not null")
    trie = some.selectExpr(f"shiftright(k, {shift1}) AS t_").distinct()
    bloom = bloom_bits(some.selectExpr(f"shiftright(k, {shift2}) AS v"), "v", bits, hashes, 3)
    ends = asked.selectExpr("q", f"shiftright(a, {shift2}) AS x", f"shiftright(b, {shift2}) AS y")
    wide = ends.where(f"y - x >= {most}").select("q", F.lit(True).alias("hit"))
    # The trie's nodes first: a part of the range under a node without keys asks nothing more.
    step = shift1 - shift2
    under = ends.where(f"y - x < {most}").select("q", "x", "y", F.explode(F.expr(f"sequence(shiftright(x, {step}), shiftright(y, {step}))")).alias("t")).join(grows(trie), F.col("t") == F.col("t_"), "left_semi")
    met = under.select("q", F.explode(F.expr(f"sequence(greatest(x, shiftleft(t, {step})), least(y, shiftleft(t + 1, {step}) - 1))")).alias("v"))
    return bloom_members(met, "v", bloom, bits, hashes, 3).select("q", F.lit(True).alias("hit")).union(wide)


def tree_bits(keys: DataFrame, shift: int, height: int, words: int, hashes: int) -> DataFrame:
    """(j, place): path bits of small trees over `height` bits above `shift`, one hashed word per tree and function."""
    nodes = keys.where("k is not null").select(F.explode(F.sequence(F.lit(0), F.lit(height))).alias("level"), "k").selectExpr(f"shiftright(k, {shift + height}) AS tree", "level", f"shiftright(k, {shift} + level) AS node").distinct()
    return tree_places(nodes, height, words, hashes).select("j", "place").distinct()


def tree_places(nodes: DataFrame, height: int, words: int, hashes: int) -> DataFrame:
    """Place of a tree node in its word: heap number of the node inside the tree."""
    inside = nodes.withColumn("heap", F.expr(f"shiftleft(1L, {height} - level) + node - shiftleft(tree, {height} - level)"))
    drawn = with_draws(inside, [(f"_d{j}", "tree", words, 300 + j) for j in range(hashes)])
    return drawn.select(*inside.columns, F.inline(F.array(*[F.struct(F.lit(j).alias("j"), (F.col(f"_d{j}") * 2 ** (height + 1) + F.col("heap")).alias("place")) for j in range(hashes)])))


def ltb_probe(bits_set: DataFrame, ranges: DataFrame, shift: int, height: int, words: int, hashes: int) -> DataFrame:
    return answered(ranges, ltb_hits(bits_set, questions(ranges), shift, height, words, hashes))


def ltb_hits(bits_set: DataFrame, asked: DataFrame, shift: int, height: int, words: int, hashes: int) -> DataFrame:
    """Cover the range, coarsened to the tree's leaves, by tree nodes; a node set in all its words means maybe."""
    coarse = asked.selectExpr("q", f"shiftright(a, {shift}) AS a", f"shiftright(b, {shift}) AS b")
    nodes = dyadic_cover(coarse, height).selectExpr("q", "level", "node", f"shiftright(node, {height} - level) AS tree")
    placed = tree_places(nodes, height, words, hashes)
    hit = placed.join(grows(bits_set.selectExpr("j AS _j", "place AS _p")), (F.col("j") == F.col("_j")) & (F.col("place") == F.col("_p")))
    return hit.groupBy("q", "level", "node").agg(F.count("*").alias("_n")).where(F.col("_n") == hashes).select("q", F.lit(True).alias("hit"))


def minmax_probe(keys: DataFrame, ranges: DataFrame) -> DataFrame:
    """Control: only the least and the greatest key are known."""
    ends = keys.agg(F.min("k").alias("_lo"), F.max("k").alias("_hi"))
    asked = questions(ranges).join(F.broadcast(ends))
    return answered(ranges, asked.select("q", ((F.col("b") >= F.col("_lo")) & (F.col("a") <= F.col("_hi"))).alias("hit")))
