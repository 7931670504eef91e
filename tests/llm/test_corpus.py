"""The corpus operators on small fixtures: odd rows, brute force, round trips, held-out accuracy."""

import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from conftest import DATA, as_rows

from rangesieve.llm import exact_dedup, jaccard_join, language_id, license_scan, line_dedup, merkle, packing, rule_quality, source_mix, toxicity
from rangesieve.llm.common import fold_of, words_of
from rangesieve.llm.queries import ORACLES, QUERIES

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, bucket string, _key int, _row int, TEXT int, size int"


def sentence(rng, n=12):
    return " ".join(rng.choice(["alpha", "beta", "gamma", "delta", "omega", "sigma", "kappa", "lambda", "theta", "zeta"]) + str(rng.randrange(50)) for _ in range(n)) + "."


@pytest.fixture(scope="module")
def odd(spark):
    rng = random.Random(1)
    long = " ".join(sentence(rng) for _ in range(4000))
    base = [sentence(rng, 60) for _ in range(6)]
    texts = [None, "", "   \n ", "One", "one", base[0], base[0], base[0].upper(), base[1], base[1].replace("alpha", "alfa", 1), long, long + " more", "Ünïcode ñ ß 中文", "a\n\nb\nc", "x" * 30_000]
    rows = [(i, t, "en", ["a", "b", None][i % 3], 0, "x", 1, 2, 3, 4) for i, t in enumerate(texts)]
    rows += [(5, base[0], "en", "c", 0, "x", 1, 2, 3, 4), (None, "no id here at all", None, None, None, None, None, None, None, None), (None, None, None, None, None, None, None, None, None, None)]
    spark.conf.set("spark.sql.caseSensitive", "true")
    yield spark.createDataFrame(rows, SCHEMA), rows
    spark.conf.set("spark.sql.caseSensitive", "false")


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(i, i % 2, (i // 2) % 2) for i in range(16)] + [(None, 1, 1), (3, None, None)], "doc_id long, quality int, toxic int")


def empty_of(df):
    return df.limit(0)


def test_exact_dedup(odd):
    df, rows = odd
    got = exact_dedup.find_copies(df).collect()
    assert len(got) == len(rows)
    norm = Counter(hashlib.sha256((r[1] or "").encode().lower()).hexdigest() for r in rows)
    assert Counter(r.text_sha256 for r in got) == norm
    for digest, n in norm.items():
        mine = [r for r in got if r.text_sha256 == digest]
        ids = [r.doc_id for r in mine if r.doc_id is not None]
        assert sum(r.kept for r in mine) == 1 and {r.group_size for r in mine} == {n}
        assert {r.keep_id for r in mine} == {max(ids) if ids else None}
    kept = exact_dedup.keep_first_copies(df)
    assert kept.columns == df.columns and kept.count() == len(norm)
    assert exact_dedup.find_copies(empty_of(df)).count() == 0


def test_perfect_hash_is_minimal_and_exact():
    keys = np.frombuffer(b"".join(hashlib.sha256(str(i).encode()).digest() for i in range(5000)), np.uint8).reshape(-1, 32)
    table = exact_dedup.PerfectHash.build(keys)
    assert sorted(table.slots(keys)) == list(range(5000))
    again = exact_dedup.PerfectHash.load(*table.dump())
    assert (again.slots(keys) == table.slots(keys)).all()


def brute_links(rows):
    def shingles(t):
        w = words_of(t)
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    sets = [shingles(r[1]) for r in rows]
    return [sum(1 for j, b in enumerate(sets) if j != i and a and b and len(a & b) / len(a | b) >= 0.8) for i, a in enumerate(sets)]


def test_jaccard_join(odd):
    df, rows = odd
    got = jaccard_join.near_groups(df).collect()
    assert sorted((str(r.doc_id), r.links) for r in got) == sorted((str(r[0]), n) for r, n in zip(rows, brute_links(rows)))
    assert jaccard_join.keep_one_of_each(df).columns == df.columns
    assert jaccard_join.near_groups(empty_of(df)).count() == 0


def test_jaccard_join_of_a_large_group(spark):
    """More near copies than a bucket and a block hold, found and counted exactly."""
    rng = random.Random(7)
    base = [f"w{i}" for i in range(120)]
    rows = []
    for i in range(1300):
        w = list(base)
        for _ in range(rng.randrange(4)):
            w[rng.randrange(len(w))] = f"e{rng.randrange(10**6)}"
        rows.append((i, " ".join(w)))
    rows += [(5000 + i, sentence(rng, 50)) for i in range(200)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.links for r in jaccard_join.near_groups(df).collect()}
    sets = [frozenset(tuple(t.split()[i : i + 5]) for i in range(len(t.split()) - 4)) for _, t in rows[:1300]]
    inter = np.zeros((1300, 1300), np.float32)
    names = {s: i for i, s in enumerate(sorted(set().union(*sets)))}
    m = np.zeros((1300, len(names)), np.float32)
    for i, s in enumerate(sets):
        m[i, [names[x] for x in s]] = 1
    inter = m @ m.T
    size = m.sum(axis=1)
    near = inter >= 0.8 * (size[:, None] + size[None, :] - inter) - 1e-6
    assert [got[i] for i in range(1300)] == (near.sum(axis=1) - 1).tolist()


def test_jaccard_join_runs_reach_the_target():
    for rare in (1.0, jaccard_join.shared_rare(jaccard_join.RARE), jaccard_join.shared_rare(jaccard_join.HALF)):
        assert jaccard_join.miss_rate(jaccard_join.runs_needed(rare), rare) <= (1 - jaccard_join.RECALL) / 2


def test_jaccard_join_of_pairs_that_share_a_passage_with_many(spark, monkeypatch):
    """Isolated pairs at about 0.85, half of whose tokens hundreds of other classes have."""
    monkeypatch.setattr(jaccard_join, "BUCKET", 32)
    rng = np.random.default_rng(12)
    sig = np.repeat(rng.integers(0, 2**32, (400, 128), dtype=np.uint32), 2, axis=0)
    sig[:, :60] = rng.integers(0, 2**32, 60, dtype=np.uint32)
    for i in range(0, len(sig), 2):
        at = rng.choice(128, 20, replace=False)
        sig[i, at] = rng.integers(0, 2**32, 20, dtype=np.uint32)
    rows = [(i, bytearray(s.tobytes()), bytearray(s.astype(np.uint8).tobytes())) for i, s in enumerate(sig)]
    edges = jaccard_join.candidate_edges(spark.createDataFrame(rows, "cls long, sig binary, low binary")).distinct().collect()
    linked = {(min(e.u, e.v), max(e.u, e.v)) for e in edges}
    assert {(i, i + 1) for i in range(0, len(sig), 2)} <= linked


def test_jaccard_join_of_pairs_in_crowded_buckets(spark, monkeypatch):
    """Isolated pairs, each of whose tokens a third of all classes have: found after several splits only."""
    monkeypatch.setattr(jaccard_join, "BUCKET", 32)
    rng = np.random.default_rng(11)
    sig = np.repeat(rng.integers(0, 3, (750, 128), dtype=np.uint32), 2, axis=0)
    for i in range(0, len(sig), 2):
        at = rng.choice(128, 26, replace=False)
        sig[i, at] = (sig[i, at] + 1) % 3
    rows = [(i, bytearray(s.tobytes()), bytearray(s.astype(np.uint8).tobytes())) for i, s in enumerate(sig)]
    edges = jaccard_join.candidate_edges(spark.createDataFrame(rows, "cls long, sig binary, low binary")).distinct().collect()
    linked = {(min(e.u, e.v), max(e.u, e.v)) for e in edges}
    assert {(i, i + 1) for i in range(0, len(sig), 2)} <= linked


def test_source_mix(odd):
    df, rows = odd
    got = source_mix.mix_sources(df).collect()
    assert len(got) == len(rows)
    total = sum(r["size"] for r in got)
    assert sum(r.taken for r in got) == total
    assert all(r.taken <= 3 * r["size"] and r.target <= 3 * r.source_size for r in got)
    assert sorted(map(str, got)) == sorted(map(str, source_mix.mix_sources(df).collect()))
    assert source_mix.mix_documents(df).columns == df.columns
    assert source_mix.mix_sources(empty_of(df)).count() == 0


def check_pieces(pieces, texts):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(packing.tokenizer_path())
    want = Counter(tuple(tok.encode(t or "", add_special_tokens=False).ids) + (1,) for t in texts)
    by_seq = {}
    for p in pieces:
        by_seq.setdefault(p.sequence_id, []).append(p)
    for seq in by_seq.values():
        at = 0
        for p in sorted(seq, key=lambda p: p.offset):
            assert p.offset == at
            at += p.length
        assert at <= packing.WINDOW and at == seq[0].sequence_length
    crcs = Counter()
    for ids, n in want.items():
        for p in {(p.start, p.length, p.ids_crc32) for p in pieces if p.doc_tokens == len(ids)}:
            if zlib.crc32(np.array(ids[p[0] : p[0] + p[1]], "<u4").tobytes()) == p[2]:
                crcs[ids] += 1
        assert crcs[ids]
    assert sum(p.length for p in pieces) == sum(len(k) * n for k, n in want.items())
    return sum(packing.WINDOW - sum(p.length for p in s) for s in by_seq.values() if sum(p.length for p in s) & (sum(p.length for p in s) - 1))


def test_packing(odd, spark):
    df, rows = odd
    assert check_pieces(packing.pack_documents(df).collect(), [r[1] for r in rows]) < 50
    hot = spark.createDataFrame([(i, "word " * 1500) for i in range(40)] + [(100 + i, "word " * (37 * i)) for i in range(20)], "doc_id long, text string")
    assert check_pieces(packing.pack_documents(hot).collect(), [r.text for r in hot.collect()]) < 50
    assert packing.pack_documents(empty_of(df)).count() == 0


def test_closest_fill_against_brute_force():
    from itertools import product

    rng = random.Random(2)
    for _ in range(40):
        counts = {rng.randrange(1, 40): rng.randrange(1, 4) for _ in range(4)}
        cap = rng.randrange(1, 90)
        best = max(s for c in product(*(range(n + 1) for n in counts.values())) if (s := sum(k * v for k, v in zip(counts, c))) <= cap)
        fill = packing.closest_fill(counts, cap)
        assert sum(k * v for k, v in fill.items()) == best and all(v <= counts[k] for k, v in fill.items())


def test_encoding_equals_the_library():
    from tokenizers import Tokenizer

    path = packing.tokenizer_path()
    tok = Tokenizer.from_file(path)
    for t in ["it's 'tis DON'T  a\x1cb ÀÉ²½ ''s x_y 12", "Σας ΟΔΟΣ", "<|endoftext|> hi", "naïve Straße ß İ ŉ 'LL", "", "é a b\u0085c"]:
        assert np.frombuffer(packing.encode(t, path), "<u4").tolist() == tok.encode(t, add_special_tokens=False).ids


def test_language_id(odd, spark):
    df, rows = odd
    got = language_id.identify_languages(df).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 for r in got)
    assert all(r.lang_pred == "und" for r in got if r.doc_id in (0, 1, 2))
    assert language_id.identify_languages(empty_of(df)).count() == 0
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    seen = language_id.identify_languages(docs).where("held_out").join(docs.select("doc_id", "lang"), "doc_id").collect()
    assert sum(r.lang == r.lang_pred for r in seen) > 0.97 * len(seen)


def test_suffix_automaton_finds_exactly_the_substrings():
    rng = random.Random(3)
    codes = [rng.randrange(3) for _ in range(60)]
    moves = language_id.suffix_automaton(codes)
    have = {tuple(codes[i:j]) for i in range(60) for j in range(i, 61)}
    for _ in range(500):
        probe = [rng.randrange(3) for _ in range(rng.randrange(1, 8))]
        state, ok = 0, True
        for c in probe:
            state = moves[state].get(c, 0)
            if state == 0:
                ok = False
                break
        assert ok == (tuple(probe) in have)


@pytest.mark.parametrize("cells", [8_000_000, 0])
def test_phrases_against_greedy_parsing(monkeypatch, cells):
    """Phrase counts equal a parse by substring search, with tables and with sorted pairs."""
    monkeypatch.setattr(language_id, "TABLE", cells)
    rng = random.Random(4)
    references = {k: "".join(rng.choice(v) for _ in range(300)) for k, v in (("x", "abc "), ("y", "bcde "), ("z", "中文字 a"))}
    parser = language_id.CrossParser(references)
    texts = ["".join(rng.choice("abcde 中文zq") for _ in range(rng.randrange(1, 80))) for _ in range(60)]
    got = parser.phrases([parser.encode(t) for t in texts])
    kept = {k: parser.encode(v.lower()).tolist() for k, v in references.items()}

    def held(reference, part):
        return any(reference[i : i + len(part)] == part for i in range(len(reference) - len(part) + 1))

    for t, counts in zip(texts, got):
        codes = parser.encode(t).tolist()
        for name, n in zip(parser.languages, counts):
            at = phrases = 0
            while at < len(codes):
                # A letter that the reference lacks opens a phrase, which goes on with the longest match after it.
                begin = end = at if held(kept[name], codes[at : at + 1]) else at + 1
                while end < len(codes) and held(kept[name], codes[begin : end + 1]):
                    end += 1
                phrases, at = phrases + 1, end
            assert n == phrases


def test_two_ideographic_languages_stay_small():
    rng = random.Random(6)
    signs = [chr(0x4E00 + i) for i in range(6000)]
    references = {"p": "".join(rng.choice(signs[:3000]) for _ in range(20_000)), "q": "".join(rng.choice(signs[3000:]) for _ in range(20_000)), "r": "latin text " * 500}
    parser = language_id.CrossParser(references)
    held = sum(x.nbytes for moves in parser.moves for x in vars(moves).values() if isinstance(x, np.ndarray))
    assert held < 50_000_000
    assert parser.predict([references["q"][50:90], references["p"][70:90], "latin"])[0] == ["q", "p", "r"]


def test_toxicity(odd, labels):
    df, rows = odd
    got = toxicity.score_toxicity(df, labels).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in got)
    assert toxicity.score_toxicity(empty_of(df), labels).count() == 0
    assert toxicity.score_toxicity(df, empty_of(labels)).count() == len(rows)


def test_toxicity_tolerates_inserted_characters():
    rng = random.Random(5)
    clean = [" ".join(rng.choice(["river", "stone", "green", "walk", "paper", "light", "house", "music", "garden", "table"]) for _ in range(30)) for _ in range(200)]
    toxic = [t + " " + rng.choice(["blockhead", "nitwit", "scoundrel"]) for t in clean[:100]]
    model = toxicity.fit(clean[100:] + toxic, [0] * 100 + [1] * 100)
    margins = toxicity.TokenMargins(model)
    margins.learn({"blockhead", "block.head", "blo*ckhead", "nit-wit", "garden", "stone"})
    assert min(margins[w] for w in ("blockhead", "block.head", "blo*ckhead", "nit-wit")) > max(margins["garden"], margins["stone"])


def test_rule_quality(odd, labels, spark):
    df, rows = odd
    got = rule_quality.score_quality(df, labels).collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for r in got)
    assert rule_quality.score_quality(df, empty_of(labels)).count() == len(rows)
    assert rule_quality.keep_good(df, labels).columns == df.columns
    sf = "/root/testdata/sf0.01"
    marks = spark.read.parquet(f"{sf}/labels.parquet")
    seen = rule_quality.score_quality(spark.read.parquet(f"{sf}/documents.parquet"), marks).where("held_out").join(marks, "doc_id").collect()
    assert sum(r.quality == r.predicted for r in seen) > 0.95 * len(seen)


def test_compiled_rules_equal_the_model(odd, labels):
    df, _ = odd
    stats = rule_quality.with_statistics(df.select("doc_id", "text"))
    x = np.array([[getattr(r.stats, n) for n in rule_quality.NAMES] for r in stats.collect()])
    y = (x[:, 1] > np.median(x[:, 1])).astype(int)
    model = rule_quality.fit(np.repeat(x, 6, axis=0), np.repeat(y, 6))
    got = [r.s for r in stats.select(model.column().alias("s")).collect()]
    assert np.allclose(got, model.predict(x))


def test_merkle(odd):
    df, rows = odd
    got = merkle.fingerprint_documents(df).collect()
    assert len(got) == len(rows)
    ordered = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0), r[1] is not None, r[1] or ""))
    want = Counter()
    for r, s in zip(ordered, ordered[1:] + ordered[:1]):
        changed = merkle.edited(r[1] or "", s[1] or "")
        want[(str(r[0]), len(r[1] or ""), hashlib.sha256(changed.encode()).hexdigest(), merkle.fingerprint(r[1]))] += 1
    assert Counter((str(r.doc_id), r.n_chars, r.edited_sha256, r.fingerprint) for r in got) == want
    assert merkle.fingerprint_documents(empty_of(df)).count() == 0
    one, two = "First one. Second.\nThird line here.\n\nLast.", "First one. Second.\nThird line changed.\n\nLast."
    assert 0 < merkle.likeness(merkle.fingerprint(one), merkle.fingerprint(two)) < 1
    assert merkle.compare(merkle.fingerprint(one), merkle.fingerprint(two))[1]


def naive_tree(text):
    """Leaves by paragraph and the words, cut by the same rules, without digests of branches."""
    return [[x for sentence in merkle._SENTENCE.findall(p) for x in merkle._pieces(sentence)] for p in (text or "").split("\n")]


def test_merkle_likeness_against_flat_leaves():
    """Compared from the root down, the likeness is that of the multisets of leaves; branches name the changed paragraphs."""
    rng = random.Random(21)
    for _ in range(60):
        paragraphs = [" ".join(sentence(rng, rng.randrange(1, 20)) for _ in range(rng.randrange(0, 6))) for _ in range(rng.randrange(20, 40))]
        other = list(paragraphs)
        changed = sorted(rng.sample(range(len(paragraphs)), 3))
        for i in changed:
            other[i] = sentence(rng, 9)
        rng.random() < 0.5 and other.insert(rng.randrange(len(other)), sentence(rng, 7))
        one, two = "\n".join(paragraphs), "\n".join(other)
        near, branches = merkle.compare(merkle.fingerprint(one), merkle.fingerprint(two))
        a, b = (Counter(x for p in naive_tree(t) for x in p) for t in (one, two))
        assert abs(near - sum((a & b).values()) / max(sum(a.values()), sum(b.values()))) < 1e-9
        where = []
        for i, section in enumerate(merkle._branches(merkle.fingerprint(one))):
            where += [f"{i}.{j}" for j in range(section[1].count("/") + 1)]
        # Every changed paragraph whose leaves are gone is named, and no other; of equal paragraphs any may be.
        named = {paragraphs[where.index(x)] for x in branches}
        gone = {paragraphs[i] for i in changed if Counter(naive_tree(paragraphs[i])[0]) - b}
        assert gone <= named <= {paragraphs[i] for i in changed}


def test_merkle_roots_test_equality():
    rng = random.Random(22)
    texts = ["", "\n", "\n\n", "a", "a\n", "\na", "a b", "ab", "a  b", "A b"] + [sentence(rng, 40) for _ in range(20)]
    roots = {merkle.fingerprint(t).partition(";")[0] for t in texts}
    assert len(roots) == len(set(texts)) and merkle.fingerprint(None) == merkle.fingerprint("")
    assert merkle.likeness(merkle.fingerprint(""), merkle.fingerprint(None)) == 1


@pytest.mark.parametrize("space", [" ", ""])
def test_merkle_of_a_long_line_without_full_stops(space):
    rng = random.Random(9)
    words = [rng.choice("abcdefgh") + str(rng.randrange(10**5)) for _ in range(1500)]
    text = space.join(words)
    assert 0.6 < merkle.likeness(merkle.fingerprint(text), merkle.fingerprint(merkle.edited(text, "z" * len(text)))) < 0.75
    one = merkle.fingerprint(space.join(words[:700] + ["new"] + words[700:]))
    assert 0.95 < merkle.likeness(merkle.fingerprint(text), one) < 1
    assert "".join(merkle._pieces(text + "  ")) == text + "  "
    assert max(len(merkle._words(x)) for x in merkle._pieces(text)) <= merkle.LEAF_WORDS + 1


def test_merkle_results_of_long_texts(spark):
    rows = [(2, " ".join(f"w{i}" for i in range(900))), (1, " ".join(f"v{i}" for i in range(900)))]
    got = {r.doc_id: r for r in merkle.fingerprint_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert all(0.6 < got[i].near_edited < 0.72 and got[i].near_next == 0 for i in (1, 2))


def test_license_scan(odd, spark):
    df, _ = odd
    assert license_scan.scan_licenses(df).count() == 0 and license_scan.scan_licenses(empty_of(df)).count() == 0
    texts = [(1, "x y z. Released under the MIT License. more"), (2, "licensed UNDER the apache license version 2.0"), (3, None), (4, " ".join(license_scan.TEMPLATES["ISC"])), (5, "the license of nothing")]
    found = {(r.doc_id, r.license) for r in license_scan.scan_licenses(spark.createDataFrame(texts, "doc_id long, text string")).collect()}
    assert found == {(1, "MIT"), (2, "Apache-2.0"), (4, "ISC")}


def test_line_dedup(spark):
    page = "<html><body><nav><li>Home</li></nav><p>text {}</p><script>x()</script></body></html>"
    rows = [(i, "http://a.example/x", page.format(i), 1) for i in range(5)] + [(9, "http://b.example/", page.format(9), 1), (10, None, None, 1), (9, "http://b.example/", page.format(9), 1)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, lines int")
    got = {(r.page_id, r.text, r.n_dropped) for r in line_dedup.dedup_lines(df).collect()}
    assert got == {(i, f"text {i}", 1) for i in range(5)} | {(9, "Home\ntext 9", 0), (10, "", 0)}
    assert line_dedup.dedup_lines(empty_of(df)).count() == 0


def test_line_dedup_of_a_hot_host_against_counting(spark):
    rng = random.Random(14)
    rows = [(i, "http://big.example/p" if i % 3 else f"http://small{i % 40}.example/", "<p>" + "</p><p>".join(["menu"] * (i % 2) + [f"line {rng.randrange(60)}" for _ in range(6)] + ["long " * 3000] * (i == 7)) + "</p>", "x") for i in range(600)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, host string")
    got = {r.page_id: r.text for r in line_dedup.dedup_lines(df).collect()}
    lines = {i: [" ".join(x.split()) for x in html[3:-4].split("</p><p>")] for i, _, html, _ in rows}
    host = {i: url for i, url, _, _ in rows}
    total = Counter(host.values())
    seen = Counter((host[i], x) for i, mine in lines.items() for x in set(mine))
    for i, mine in lines.items():
        assert got[i] == "\n".join(x for x in mine if not (seen[host[i], x] >= line_dedup.PAGES and seen[host[i], x] > line_dedup.RATIO * total[host[i]]))


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_matches_sql(spark, duck, name):
    assert as_rows(QUERIES[name](spark, DATA).toPandas()) == as_rows(duck.sql(ORACLES[name]).df())


def test_folds():
    assert fold_of(12, 5) == zlib.crc32(b"12") % 5


def test_pipeline(spark):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    marks = {r.doc_id: r.quality for r in spark.read.parquet(f"{DATA}/labels.parquet").collect()}
    kept = {r.doc_id for r in cp.quality(spark, docs, DATA).collect()}
    assert sum((i in kept) == bool(q) for i, q in marks.items()) > 0.9 * len(marks)
    once = cp.exact(spark, docs, DATA).collect()
    assert len({(r.text or "").lower() for r in once}) == len(once)
    assert cp.run(spark, DATA).count() > 0


def test_pipeline_near_dedup_against_brute_force(spark):
    import corpus_pipeline as cp

    rng = random.Random(13)
    base = [sentence(rng, 60) for _ in range(8)]
    texts = [b.replace(b.split()[at], "changed", 1) for b in base for at in (0, 20, 59)] + base + [None, "", sentence(rng, 4)]
    rows = [(i, t) for i, t in enumerate(texts)]
    sets = [{tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} if (w := words_of(t)) else set() for _, t in rows]
    group = list(range(len(rows)))
    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if a and b and len(a & b) >= 0.8 * len(a | b):
                group = [min(group[i], group[j]) if g in (group[i], group[j]) else g for g in group]
    assert len(set(group)) < len(rows)
    got = cp.near(spark, spark.createDataFrame(rows, "doc_id long, text string"), DATA).collect()
    assert sorted(r.doc_id for r in got) == sorted(set(group))


def naive_mix(rows):
    """Copies that the mix takes of each (doc_id, source, text), served one by one."""
    size = {i: len(re.findall(source_mix.WORD_RUN, t or "")) for i, _, t in rows}
    names = sorted({s for _, s, _ in rows if s is not None}) + [None] * any(s is None for _, s, _ in rows)
    words = {s: sum(size[i] for i, x, _ in rows if x == s) for s in names}
    weight = {s: source_mix.WEIGHTS[k % 3] for k, s in enumerate(names)}
    budget, capped = sum(words.values()), set()
    while True:
        left, share = budget - sum(3 * words[s] for s in capped), sum(weight[s] for s in names if s not in capped)
        full = {s for s in names if s not in capped and 3 * words[s] * share <= left * weight[s]}
        if not full:
            break
        capped |= full
    served = []
    for rank, s in enumerate(names):
        target = float(3 * words[s]) if s in capped else left / share * weight[s]
        upto = 0
        for i in sorted((i for i, x, _ in rows if x == s), key=lambda i: (hashlib.md5(f"mix{i}".encode()).hexdigest(), i)):
            upto += size[i]
            served += [((e * words[s] + upto) / target, rank, upto, e, i) for e in range(3) if size[i]]
    taken, copies = 0, Counter(i for i in size if not size[i])
    for *_, i in sorted(served):
        if taken < budget:
            copies[i] += 1
            taken += size[i]
    return copies


def test_pipeline_mix_against_serving_one_by_one(spark):
    import corpus_pipeline as cp

    rng = random.Random(17)
    rows = [(i, rng.choice(["a", "a", "a", "b", "c", "d", None]), rng.choice([None, "", " \t", sentence(rng, rng.randrange(1, 200))]) if i % 9 == 0 else sentence(rng, rng.randrange(1, 200))) for i in range(300)]
    got = cp.mix(spark, spark.createDataFrame(rows, "doc_id long, source string, text string"), DATA).collect()
    assert Counter(r.doc_id for r in got) == naive_mix(rows)


def naive_near(rows):
    """Of rows (doc_id, text, ...), the one with the least doc_id of each group of linked texts."""
    sets = [{tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} if (w := words_of(r[1])) else set() for r in rows]
    group = list(range(len(rows)))
    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            if a and b and min(len(a), len(b)) >= 0.8 * max(len(a), len(b)) and group[i] != group[j] and len(a & b) >= 0.8 * len(a | b):
                one, two = group[i], group[j]
                group = [one if g == two else g for g in group]
    best = {}
    for r, g in zip(rows, group):
        best[g] = min(best.get(g, r), r, key=lambda x: x[0])
    return sorted(best.values(), key=lambda r: r[0])


def test_pipeline_run_against_plain_python(spark):
    """All that follows the classifier, done again in plain Python from what the classifier kept."""
    import corpus_pipeline as cp

    kept = cp.quality(spark, spark.read.parquet(f"{DATA}/documents.parquet"), DATA).collect()
    last = {}
    for r in sorted(kept, key=lambda r: r.doc_id):
        last[re.sub("[A-Z]", lambda c: c[0].lower(), r.text or "")] = (r.doc_id, r.text, r.source)
    near = naive_near(list(last.values()))
    assert len(near) < len(last) < len(kept)
    copies = naive_mix([(i, s, t) for i, t, s in near])
    text_of = {i: t for i, t, _ in near}
    pieces = cp.run(spark, DATA).collect()
    assert set(copies) == {p.doc_id for p in pieces if p.doc_id in copies} == {p.doc_id for p in pieces}
    tokens = {p.doc_id: p.doc_tokens for p in pieces}
    laid = Counter()
    for p in pieces:
        laid[p.doc_id] += p.length
    assert laid == Counter({i: n * tokens[i] for i, n in copies.items()})
    check_pieces(pieces, [text_of[i] for i, n in copies.items() for _ in range(n)])


def test_toxicity_of_held_out_rows(spark):
    sf = "/root/testdata/sf0.01"
    marks = spark.read.parquet(f"{sf}/labels.parquet")
    seen = toxicity.score_toxicity(spark.read.parquet(f"{sf}/documents.parquet"), marks).where("held_out").join(marks, "doc_id").collect()
    for kind, least in ((1, 0.7), (0, 0.95)):
        mine = [r.predicted == kind for r in seen if r.toxic == kind]
        assert mine and sum(mine) >= least * len(mine)


@pytest.mark.parametrize("few", [10**6, 1])
def test_components_from_forests_of_tasks(spark, few):
    from rangesieve.llm.components import connected_components, stars

    rng = np.random.default_rng(3)
    pairs = [(int(x), int(y)) for x, y in rng.integers(-300, 300, (260, 2))] + [(k, k + 1) for k in range(1000, 1080)] + [(7, 7), (5000, 5000)]
    want = dict(stars(np.array(pairs)).tolist())
    parent = {x: x for p in pairs for x in p}
    for _ in parent:
        for x, y in pairs:
            parent[x] = parent[y] = min(parent[x], parent[y])
    assert want == {x: y for x, y in parent.items() if x != y}
    edges = spark.createDataFrame(pairs, "u long, v long").repartition(5)
    got = [tuple(r) for r in connected_components(edges, few=few).collect()]
    joined = {x for p in pairs if p[0] != p[1] for x in p}
    assert sorted(got) == sorted((x, parent[x]) for x in joined)


def test_pairs_of_long_buckets_connect_what_all_pairs_connect():
    rng = np.random.default_rng(4)
    low = rng.integers(0, 256, (400, jaccard_join.POSITIONS)).astype(np.uint8)
    for i in range(1, 300):  # chains and bushes of near rows, some pairs just at the link level
        low[i] = low[rng.integers(max(0, i - 5), i)]
        low[i, rng.choice(jaccard_join.POSITIONS, rng.integers(0, 60), replace=False)] += 1
    link = jaccard_join.BUCKET_LINK
    same = (low[:, None] == low[None]).sum(axis=2)
    assert all((jaccard_join._agree(low[i], low) == same[i]).all() for i in range(0, 400, 37))
    x, y = np.nonzero(same >= link * jaccard_join.POSITIONS)
    want = jaccard_join._forest(np.stack([x, y], axis=1)[x < y])
    got = jaccard_join._near_pairs(np.array([0]), np.array([400]), low, link)
    assert len(got) < len(want) + 1 and (same[got[:, 0], got[:, 1]] >= link * jaccard_join.POSITIONS).all()
    assert jaccard_join._forest(got).equals(want) or as_rows(jaccard_join._forest(got)) == as_rows(want)
