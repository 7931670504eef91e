"""Document fingerprints as Merkle trees over sections, paragraphs and pieces of sentences.

A paragraph is a line. A section ends with a paragraph whose hash says so (one in four on average) or before an empty
line, so an edit moves no distant section border. Leaves are pieces of sentences of up to LEAF_WORDS words, cut at words
whose hash says so; texts of few words also get a leaf for each word. A node's digest covers its children's whole
digests, so equal roots mean equal texts, and differing branches lead to an edit.

The fingerprint is one string: root, then the sections, each with its paragraphs' leaves. Two fingerprints are compared
from the root down: equal branches are left closed, differing ones are opened. Their likeness is the share of leaves in
common, as multisets, and the branches that stay different are where the edit is.

The query pairs each document with the next one by descending id. Documents are dealt into ranges of ids, ordered in
each range, and read in order; the first document of a range is also sent to the range before it. The number of ranges
follows the amount of text.

Defined cases: null text counts as empty, whose tree is one empty paragraph, and two empty texts are alike by 1; a
null id comes last in descending order; rows that share an id are ordered by their text; a single document is its own
next one; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rangesieve.llm.common import own, ship_package, shuffle_width
from rangesieve.operators.order import with_shard

SECTION_ENDS = 4
FEW_WORDS = 128
PIECE_ENDS = 8
LEAF_WORDS = 16
WORD_LETTERS = 32  # letters of a word that is never cut, and of a part of a longer one
_SENTENCE = re.compile(r"[^.!?…]*[.!?…]+[\s]*|[^.!?…]+")
_WORD = re.compile(r"\s*\S+(?:\s+\Z)?|\s+")


RANGE_CHARS = 32_000_000  # text of a range of ids


def _digest(text: str) -> bytes:
    return xxhash.xxh3_128_digest(text.encode("utf-8", "surrogatepass"))


def _leaf(text: str) -> str:
    return _digest(text).hex()[:10]


def _ends(text: str) -> bool:
    return xxhash.xxh3_64_intdigest(text.encode("utf-8", "surrogatepass")) % PIECE_ENDS == 0


def _words(text: str) -> list[str]:
    """The words with the white space before them, long ones in parts that end with two letters whose hash says so."""
    out = []
    for w in _WORD.findall(text):
        if len(w) <= WORD_LETTERS:
            out.append(w)
            continue
        start = 0
        for i in range(2, len(w)):
            if i - start >= WORD_LETTERS or i - start >= 2 and _ends(w[i - 2 : i]):
                out.append(w[start:i])
                start = i
        out.append(w[start:])
    return out


def _pieces(sentence: str) -> Iterator[str]:
    words, start = _words(sentence), 0
    for i, w in enumerate(words, 1):
        if i == len(words) or i - start >= LEAF_WORDS or _ends(w):
            yield "".join(words[start:i])
            start = i


def _node(kind: bytes, children: list[bytes]) -> bytes:
    return hashlib.sha256(kind + b"".join(children)).digest()[:16]


def fingerprint(text: str | None) -> str:
    """root ; words ; section | section ...; a section is digest=paragraph/paragraph, a paragraph leaf.leaf.leaf"""
    text = text or ""
    sections, current = [], []
    for p in text.split("\n"):
        leaves = [_digest(x) for sentence in _SENTENCE.findall(p) for x in _pieces(sentence)]
        node = _node(b"p", leaves)
        if not p and current:
            sections.append(current)
            current = []
        current.append((node, leaves))
        if node[0] % SECTION_ENDS == 0:
            sections.append(current)
            current = []
    if current:
        sections.append(current)
    inner = [_node(b"s", [n for n, _ in s]) for s in sections]
    few = _words(text) if len(text.split(None, FEW_WORDS)) <= FEW_WORDS else []
    words = ".".join(map(_leaf, few)) if len(few) <= FEW_WORDS else ""
    printed = "|".join(f"{h.hex()[:16]}=" + "/".join(".".join([x.hex()[:10] for x in leaves]) for _, leaves in s) for h, s in zip(inner, sections))
    return f"{_node(b'r', inner).hex()};{words};{printed}"


def _branches(print_: str) -> list[tuple[str, str]]:
    """(digest, paragraphs) of each section."""
    return [tuple(s.split("=", 1)) for s in print_.split(";", 2)[2].split("|")]


def _apart(one: list, two: list) -> tuple[list[int], list[int]]:
    """Places in two lists of what the other lacks, as multisets."""
    left, right = Counter(one), Counter(two)
    spare = [left - right, right - left]
    out: tuple[list[int], list[int]] = ([], [])
    for side, (items, gone) in enumerate(zip((one, two), spare)):
        for i in range(len(items) - 1, -1, -1):
            if gone[items[i]] > 0:
                gone[items[i]] -= 1
                out[side].append(i)
    return out[0][::-1], out[1][::-1]


def _leaves_of(paragraphs: str) -> int:
    return sum(p.count(".") + 1 for p in paragraphs.split("/") if p)


def compare(one: str, two: str) -> tuple[float, list[str]]:
    """(likeness, branches): from the roots down. Branches are `section.paragraph` of `one`, those with a leaf that `two`
    lacks (or a paragraph without leaves that it lacks); none for equal roots. Where both texts have few words, the
    likeness counts words."""
    if one.partition(";")[0] == two.partition(";")[0]:
        return 1.0, []
    a, b = _branches(one), _branches(two)
    open_a, open_b = _apart([s[0] for s in a], [s[0] for s in b])
    below_a = [(f"{i}.{j}", p) for i in open_a for j, p in enumerate(a[i][1].split("/"))]
    below_b = [p for i in open_b for p in b[i][1].split("/")]
    other_a, other_b = _apart([p for _, p in below_a], below_b)
    leaves_a = [(name, x) for i in other_a for name, p in [below_a[i]] for x in p.split(".")]
    leaves_b = [x for i in other_b for x in below_b[i].split(".")]
    lost_a, lost_b = _apart([x for _, x in leaves_a], leaves_b)
    branches = list(dict.fromkeys(leaves_a[i][0] for i in lost_a))
    few = one.split(";", 2)[1], two.split(";", 2)[1]
    if all(few):
        x, y = Counter(few[0].split(".")), Counter(few[1].split("."))
        return sum((x & y).values()) / max(sum(x.values()), sum(y.values())), branches
    total_a, total_b = (sum(_leaves_of(s[1]) for s in t) for t in (a, b))
    lost = sum(leaves_a[i][1] != "" for i in lost_a)
    return (total_a - lost) / max(total_a, total_b, 1), branches


def likeness(one: str, two: str) -> float:
    return compare(one, two)[0]


_FIELDS = [("doc_id", T.LongType()), ("n_chars", T.LongType()), ("edited_sha256", T.StringType()), ("fingerprint", T.StringType()), ("edited_fingerprint", T.StringType()), ("near_edited", T.DoubleType()), ("near_next", T.DoubleType()), ("edited_branches", T.StringType())]
PRINTS = T.StructType([T.StructField(*f) for f in _FIELDS])


def edited(text: str, following: str) -> str:
    """The last third of a text replaced by as many first code points of the following text, or all it has."""
    k = len(text) // 3
    return text[: len(text) - k] + following[:k]


def _prints(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (range, ghost, doc_id, text) in order; a ghost closes its range and has no row of its own."""
    before, out = None, []

    def close(now):
        text, following = before[3] or "", now[3] or ""
        changed = edited(text, following)
        mine, other, after = before[4], fingerprint(changed), now[4]
        near, branches = compare(mine, other)
        return (before[2], len(text), hashlib.sha256(changed.encode("utf-8", "surrogatepass")).hexdigest(), mine, other, near, likeness(mine, after), ",".join(branches))

    for batch in batches:
        columns = batch.to_pydict()
        for row in zip(columns["range"], columns["ghost"], columns["doc_id"], columns["text"]):
            now = (*row, fingerprint(row[3]))
            if before is not None and before[0] == now[0] and not before[1]:
                out.append(close(now))
            before = now
            if len(out) >= 200:
                yield pa.record_batch([pa.array(c, f.type) for c, f in zip(zip(*out), _ARROW)], schema=_ARROW)
                out = []
    if out:
        yield pa.record_batch([pa.array(c, f.type) for c, f in zip(zip(*out), _ARROW)], schema=_ARROW)


_ARROW = pa.schema([("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64()), ("edited_branches", pa.string())])
NO_ID = -(2**63)


def fingerprint_documents(docs: DataFrame) -> DataFrame:
    """One row per document: the columns of PRINTS; edited_branches names the paragraphs (section.paragraph) of the text in
    which the edited text differs."""
    spark = docs.sparkSession
    ship_package(spark)
    rows = own(docs, "doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.coalesce(F.col("doc_id").cast("long"), F.lit(NO_ID)).alias("key"))
    chars = rows.agg(F.sum(F.octet_length("text")).alias("c")).first().c or 0
    n = max(shuffle_width(spark) * 2, -(-chars // RANGE_CHARS))
    cuts = rows.agg(F.percentile_approx("key", [i / n for i in range(1, n)], 20 * n).alias("q")).first().q or []
    bounds = sorted(set(cuts))
    placed = with_shard(rows, "key", bounds, "_up").withColumn("range", (F.lit(len(bounds)) - F.col("_up")).cast("int")).drop("_up")
    heads = {r.range: r.head for r in placed.groupBy("range").agg(F.max("key").alias("head")).collect()}  # a row a range
    if not heads:
        return spark.createDataFrame([], PRINTS)
    order = sorted(heads)
    # The head of a range also closes the range before it; the first head closes the last range.
    before = {order[i]: order[i - 1] for i in range(len(order))}
    every = range(len(bounds) + 1)
    table = lambda found: "array(" + ", ".join(f"{found[i]}L" if i in found else "CAST(null AS BIGINT)" for i in every) + ")"
    lowest = f"(-{2**63 - 1}L - 1L)"  # SQL has no literal for it
    head = table(heads).replace(f"{NO_ID}L", lowest)
    target = F.expr(f"if(key = {head}[range], CAST({table(before)}[range] AS INT), null)")
    here, there = F.struct(F.col("range"), F.lit(False).alias("ghost")), F.struct(F.col("_to").alias("range"), F.lit(True).alias("ghost"))
    aimed = placed.withColumn("_to", target).withColumn("place", F.explode(F.when(F.col("_to").isNull(), F.array(here)).otherwise(F.array(here, there))))
    dealt = aimed.select(F.col("place.range").alias("range"), F.col("place.ghost").alias("ghost"), "doc_id", "text", "key")
    ordered = dealt.repartition(n, "range").sortWithinPartitions("range", "ghost", F.col("key").desc(), F.col("text").asc_nulls_first())
    return ordered.select("range", "ghost", "doc_id", "text").mapInArrow(_prints, PRINTS)
