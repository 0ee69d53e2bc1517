"""The pipeline's near-duplicate stage against all pairs of exact sets."""

from __future__ import annotations

import random
from collections import Counter

import corpus_pipeline
import pytest
from brute import WORD, lower

from pointloom.llm import linededup, neardup, simhash

SF = "/root/testdata/sf0.001"
COLUMNS = "doc_id long, text string"
FAR = 2**63 - 1


def shingles(text):
    words = WORD.findall(lower(text))
    return {tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))} if words else set()


def kept(rows):
    """Smallest ids of the components of all pairs with a similarity of 0.8 or more; no id is the largest."""
    sets = [(i, shingles(t)) for i, t in rows]
    label = list(range(len(sets)))
    for x, (_, a) in enumerate(sets):
        for y, (_, b) in enumerate(sets[:x]):
            if 5 * len(a & b) >= 4 * len(a | b) and (bool(a) == bool(b)):
                old, new = label[x], label[y]
                label = [new if k == old else k for k in label]
    least = {}
    for (i, _), k in zip(sets, label, strict=True):
        i = FAR if i is None else i
        least[k] = min(i, least.get(k, i))
    return sorted(-1 if i == FAR else i for i in least.values())


def got(spark, rows):
    docs = spark.createDataFrame(rows, COLUMNS).repartition(3)
    return sorted(-1 if r.doc_id is None else r.doc_id for r in corpus_pipeline.simhash_stage(spark, docs, SF).collect())


def edited(rng, words, times):
    words = list(words)
    for at in rng.sample(range(len(words)), times):
        words[at] = f"new{rng.random()}"
    return words


def test_pairs_around_the_bound(spark):
    rng, rows = random.Random(5), []
    for k in range(60):
        words = [f"w{rng.randrange(10**6)}" for _ in range(rng.choice([5, 8, 60, 200, 400]))]
        rows.append((10 * k, " ".join(words)))
        rows += [(10 * k + j, " ".join(edited(rng, words, max(1, len(words) * j // 200)))) for j in range(1, 7)]
    # nine shingles, of which eight are shared by one that is a word shorter, and ten with eight in common: 8/9, and 8/10 just at the bound
    rows += [(1000, "a b c d e f g h i j k l m"), (1001, "A b c d e f g h i j k l"), (1002, "b c d e f g h i j k l m n"), (1003, "z"), (1004, "Z"), (1005, None), (1006, " "), (None, "z")]
    want = kept(rows)
    assert 60 < len(want) < len(rows) - 60
    assert got(spark, rows) == want


def test_hub_of_frequent_shingles(spark):
    rng = random.Random(7)
    common = " ".join(f"c{k}" for k in range(40))
    rows = [(k, common + " " + " ".join(f"u{k}x{j}" for j in range(rng.choice([2, 6, 30])))) for k in range(300)]
    assert got(spark, rows) == kept(rows)


def near_copies(rng, n, words, times):
    """Copies of one text whose changes put some pairs above the bound and some below it."""
    return [(k, " ".join(edited(rng, words, times))) for k in range(n)]


@pytest.mark.parametrize("bucket", [2000, 12])
def test_large_group_of_near_copies(spark, monkeypatch, bucket):
    """Also where the group is cut into buckets."""
    monkeypatch.setattr(neardup, "BUCKET", bucket)
    rng = random.Random(21)
    words = [f"w{k}" for k in range(90)]
    rows = near_copies(rng, 120, words, 2) + [(1000 + k, t) for k, t in near_copies(rng, 60, words[:45] + [f"v{k}" for k in range(45)], 1)]
    want = kept(rows)
    assert 1 < len(want) < 100
    assert got(spark, rows) == want


def test_completion_gives_no_pairs(spark):
    rng = random.Random(22)
    rows = near_copies(rng, 200, [f"w{k}" for k in range(90)], 1)
    docs = spark.createDataFrame(rows, COLUMNS)
    named = neardup._rows(docs).withColumn("vertex", neardup.F.col("row"))
    classes = spark.createDataFrame([], "vertex long, root long")
    # nearly all of the 19 900 pairs are similar
    assert 199 <= neardup._second_pass(docs, named, classes).count() < 2000


def test_leading_shingles_of_every_set(spark, monkeypatch):
    """By number of sets that hold a shingle, whatever the chunks."""
    monkeypatch.setattr(neardup, "CHUNK_SHINGLES", 150)
    rng = random.Random(23)
    words = [f"w{k}" for k in range(60)]
    rows = [(k, " ".join(edited(rng, words, 1 + k % 9))) for k in range(60)]
    sets = {i: neardup.shingle_set(t) for i, t in rows}
    df = Counter(h >> 32 for s in sets.values() for h in s.tolist())
    want = set()
    for s in sets.values():
        order = sorted((df[h >> 32], h >> 32) for h in s.tolist())
        lead = order[: len(s) - -(-4 * len(s) // 5) + 1]
        want |= {(h, len(s), len(s) - k) for k, (n, h) in enumerate(lead) if n > 1}
    docs = spark.createDataFrame(rows, COLUMNS).repartition(3)
    got_rows = neardup.leading_shared(docs, docs.where("false").selectExpr("doc_id", "doc_id as key")).collect()
    assert {(r.s, r.n, r.left) for r in got_rows} == want and len(want) > 30


def test_rows_that_share_an_id(spark):
    """A unique text does not go with a copy that has its id, and repeated rows and rows without an id leave one row."""
    a, b, c = (" ".join(f"{x}{k}" for k in range(30)) for x in "abc")
    rows = [(1, a, "x"), (2, a, "x"), (2, b, "y"), (3, c, "z"), (3, c, "z"), (None, c, "n"), (None, b + " more", "n"), (None, "own text", "n"), (None, "own text", "n")]
    for keep in (neardup.keep_one, simhash.keep_one):
        out = keep(spark.createDataFrame(rows, "doc_id long, text string, root string").repartition(3)).collect()
        kept_rows = sorted((-1 if r.doc_id is None else r.doc_id, r.text, r.root) for r in out)
        assert [r for r in kept_rows if "more" not in r[1]] == sorted([(1, a, "x"), (2, b, "y"), (3, c, "z"), (-1, "own text", "n")])


def test_table_rows_and_no_rows(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    for part in (docs, linededup.dedup(docs)):
        rows = [tuple(r) for r in part.collect()]
        assert got(spark, rows) == kept(rows)
    assert neardup.keep_one(docs.where("false")).collect() == []


def test_counts_never_rule_out_a_similar_pair():
    rng = random.Random(9)
    for size in (1, 4, 5, 9, 100, 3000):
        words = [f"w{rng.randrange(10**6)}" for _ in range(size + 4)]
        a = neardup.shingle_set(" ".join(words))
        for times in range(0, size // 20 + 2):
            b = neardup.shingle_set(" ".join(edited(rng, words, min(times, size))))
            shared = len(set(a.tolist()) & set(b.tolist()))
            alike = 5 * shared >= 4 * (len(a) + len(b) - shared)
            assert neardup.similar(a, b) == alike
            block = neardup._Block([(1, 0, a), (2, 0, b)], False)
            assert block.group([(1, len(a), 1), (2, len(b), 2)]) == ([(1, 2)] if alike else [])
