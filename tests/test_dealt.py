"""Filters built from arrays of keys equal those built from rows."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from rangesieve.functions.hashing import SPARK, h_values, mixed, mixed_values, params_for_budget
from rangesieve.operators import bitmaps, dealt, tuning
from rangesieve.operators import filters as f
from rangesieve.plans import methods as m
from rangesieve.plans import workloads as w


@pytest.fixture(scope="module", autouse=True)
def small_arrays():
    """Several cells, shards and tasks on few keys."""
    kept = dealt.ARRAY, dealt.TOGETHER
    dealt.ARRAY, dealt.TOGETHER = 300, 700
    yield
    dealt.ARRAY, dealt.TOGETHER = kept


@pytest.fixture(scope="module")
def keys(spark):
    """2,000 keys below 2^20 in ragged steps, some of them twice, and a null."""
    some = np.unique(mixed_values(np.arange(2_000), 2**20, 3))
    rows = [(int(k),) for k in some] + [(int(k),) for k in some[::7]] + [(None,)]
    return some, spark.createDataFrame(rows, "k long").repartition(3).cache()


STARTS = np.arange(0, 2**20, 2**17)


def test_mixing_draws_of_arrays():
    x = np.concatenate([np.arange(-12, 1_200), np.array([2**62 - 1, -(2**62), 10**18 - 1, 10**18, 2**60])])
    for modulus, stream in ((2**60, 12), (10, 6), (2**60 - 32, 150)):
        sums = [hashlib.md5(f"{stream}:{v}".encode()).hexdigest() for v in x.tolist()]
        assert mixed_values(x, modulus, stream).tolist() == [(int(h[:15], 16) + int(h[15], 16) % 4 * 2**60) % modulus for h in sums]


def test_drawn_keys_are_those_of_the_rows(spark):
    got = np.concatenate([np.frombuffer(r.k, np.int64) for r in dealt.drawn(spark, 1_000, 60, 12, 3).collect()])
    assert sorted(got.tolist()) == sorted(r.k for r in spark.range(1_000).selectExpr(f"{mixed(SPARK, 'id', 2**60, 12)} AS k").collect())


@pytest.mark.parametrize("tasks", (1, 2, 4, 8))
def test_codes_are_built_alike_in_any_number_of_tasks(spark, keys, tasks):
    some, k = keys
    p = params_for_budget(len(some), 8, 2**20)
    starts = dealt.even(0, p.r - 1, len(some), 150)
    built = dealt.code_set(dealt.arrays(k), [lambda k: h_values(k, p)], starts, p.r - 1, tasks)
    assert len(starts) > 8 and built.rdd.getNumPartitions() <= tasks
    assert dealt.unpacked(built, starts, p.r - 1).tolist() == sorted(r.z for r in f.lhf_codes(k, p).collect())
    assert dealt.code_set(dealt.arrays(k.limit(0)), [lambda k: k], starts, p.r - 1, tasks).count() == 0


@pytest.mark.parametrize("held", (2**27, 0))
def test_bitmaps_hold_the_places_of_the_rows(spark, keys, monkeypatch, held):
    some, k = keys
    monkeypatch.setattr(dealt, "HELD", held)
    monkeypatch.setattr(dealt, "STRETCH", 2**11)
    a = dealt.arrays(k)
    size, words = 12 * len(some), m.tree_words(len(some), 12)

    def places(df):
        return sorted(r["shard"] * 2**11 + int(i) for r in df.collect() for i in np.flatnonzero(np.unpackbits(np.frombuffer(bytes(r["bits"]), np.uint8), bitorder="little")))

    assert places(dealt.bitmap(a, bitmaps.level_places([3, 1, 1], size), size, 3)) == sorted(r.place for r in f.level_bits(k, [3, 1, 1], size).collect())
    tree = dealt.bitmap(a, bitmaps.tree_places(2, 4, words, 2), words * 2 << 5, 3)
    assert places(tree) == sorted(r.j * (words << 5) + r.place for r in f.tree_bits(k, 2, 4, words, 2).collect())
    bloom = f.bloom_bits(k.where("k is not null").selectExpr("shiftright(k, 3) AS v"), "v", size, 4, 3)
    assert places(dealt.bitmap(a, bitmaps.prefix_places(3, size, 4), size, 3)) == sorted(r.place for r in bloom.collect())


def test_keys_in_order_tell_what_rows_tell(spark, keys):
    some, k = keys
    kept = k.where("k is not null").distinct()
    assert sorted(np.concatenate([np.frombuffer(r.k, np.int64) for r in dealt.scattered(dealt.arrays(k), 20, 2_000, 3).collect()]).tolist()) == some.tolist()
    with dealt.ordered(dealt.arrays(k), STARTS, 2**20 - 1, 3) as inside:
        assert inside.n == len(some) and dealt.parted(inside) == f.parted(kept)
        for suffix in (0, 3):
            found = []
            for r in dealt.trie_leaves(inside, suffix).collect():
                z = np.frombuffer(r.bits, np.int64, r.n)
                found += zip(z.tolist(), np.frombuffer(r.bits, np.uint8)[8 * r.n :].tolist())
            assert sorted(found) == sorted((r.z, r.s) for r in f.ttf_leaves(kept, suffix).collect())
        codes = np.concatenate([np.frombuffer(r.bits, np.int64) for r in sorted(dealt.learned_codes(inside, 64, 64 * 4).collect())])
        assert codes.tolist() == sorted(r.z for r in f.lbf_codes(kept, f.lbf_knots(kept, 64), 64, 4).collect())

        def ends(k):
            return k + mixed_values(k, 40, 9), k + mixed_values(k, 40, 9) + 31

        drawn = kept.selectExpr(f"k + {mixed(SPARK, 'k', 40, 9)} AS a").selectExpr("a", "a + 31 AS b")
        assert dealt.nearest(inside, dealt.arrays(kept), ends) == tuning.alike(kept, w.keep_empty(kept, drawn))


def test_filters_asked_together_count_as_each_alone(spark, keys):
    from rangesieve.plans import experiments as e

    some, k = keys
    s = m.Setup(spark, "", "order_key", k.where("k is not null").distinct().cache()).warm()
    drawn = s.k.selectExpr("k AS qid", f"k + {mixed(SPARK, 'k', 40, 9)} AS a", "1 + 31 * (k % 2) AS len").selectExpr("qid", "a", "a + len - 1 AS b", "len")
    made = drawn.union(s.k.selectExpr("-k - 1", "k - 900", "k + 900", "1801L")).cache()
    r, sample = e.Batch(made, "len"), s.tuned_on(made)
    got = e.all_budgets(s, m.METHODS, [8, 14], r, sample)
    alone = e.every([e.cells((name, bits), s, name, bits, r, sample) for bits in (8, 14) for name in m.METHODS])
    assert len(got) == 2 * 3 * len(m.METHODS) and sorted(got) == sorted(alone)
    assert len({x[-1] for x in got}) > 10


def test_the_package_is_sent_once_by_jobs_beside_each_other(spark, monkeypatch):
    import time
    from concurrent.futures import ThreadPoolExecutor

    from rangesieve.functions.ship import ship

    sent = []
    monkeypatch.setattr(spark.sparkContext, "_rangesieve_sent", False, raising=False)
    monkeypatch.setattr(spark.sparkContext, "addPyFile", lambda path: (time.sleep(0.2), sent.append(path)))
    with ThreadPoolExecutor(4) as pool:
        list(pool.map(ship, [spark] * 4))
    assert len(sent) == 1


def test_gathered_keys_give_the_same_counts_samples_and_answers(spark, keys):
    from rangesieve.plans import experiments as e

    _, k = keys
    k = k.where("k is not null").distinct().cache()
    one, two = m.Setup(spark, "", "order_key", k), m.Setup(spark, "", "order_key", k).gather()
    drawn = k.selectExpr("k AS qid", f"k + {mixed(SPARK, 'k', 40, 9)} AS a", "1 + 31 * (k % 2) AS len").selectExpr("qid", "a", "a + len - 1 AS b", "len").union(k.selectExpr("-k - 1", "k - 900", "k + 900", "1801L"))
    odd = drawn.union(spark.sql("SELECT 1L, CAST(NULL AS BIGINT), 5L, 7L UNION ALL SELECT 2L, 9L, 4L, 7L")).cache()
    assert (one.parted, one.n, one.inner, one.spaced) == (two.parted, two.n, two.inner, two.spaced) and one.alike(odd) == two.alike(odd)
    rows = lambda df: sorted(map(str, df.collect()))
    assert rows(one.keep_empty(odd)) == rows(two.keep_empty(odd)) != []
    sample = one.tuned_on(drawn)
    for name in m.METHODS:
        assert rows(m.answer(one, name, 12, odd, sample)) == rows(m.answer(two, name, 12, odd, sample)), name
    r = e.Batch(drawn, "len")
    assert sorted(e.all_budgets(two, m.METHODS, [8], r, sample)) == sorted(e.every([e.cells((name, 8), one, name, 8, r, sample) for name in m.METHODS]))
