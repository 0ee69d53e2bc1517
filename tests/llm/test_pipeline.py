"""The pipeline's stages by themselves and together, and the queries' SQL."""

from __future__ import annotations

import hashlib

import corpus_pipeline
import duckdb
import numpy as np
import public_tokenizers
import pytest
from brute import WORD
from test_neardup import kept
from test_text_ops import plain_lines, plain_statistics, walked

from pointloom.llm import bpe, quality, queries

SF = "/root/testdata/sf0.001"


def test_stages_do_what_they_say(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    seen = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = docs.count()
        docs = stage(spark, docs, SF)
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        docs = corpus_pipeline.materialize(docs)
        seen[name] = (before, docs.count())
    assert 0.7 * seen["quality_classifier"][0] < seen["quality_classifier"][1] < seen["quality_classifier"][0]
    assert seen["line_dedup"][0] == seen["line_dedup"][1]
    assert seen["simhash_near_dedup"][1] < seen["simhash_near_dedup"][0]
    tokens = corpus_pipeline.STAGES[-1][1](spark, docs, SF)
    assert tokens.count() == docs.count()
    assert corpus_pipeline.run(spark, SF).count() == docs.count()


def plain_stages(model, rows):
    """The five stages by plain versions of their operators, on (doc_id, text, source)."""
    rows = [r for r in rows if walked(model, np.array(plain_statistics(r[1]), np.float32)) >= quality.THRESHOLD]
    yield rows
    kept_lines = [x[-1] for x in plain_lines(rows)]
    rows = [(i, None if t is None else new, s) for (i, t, s), new in zip(rows, kept_lines, strict=True)]
    yield rows
    stay = set(kept([(i, t) for i, t, _ in rows]))
    rows = [r for r in rows if r[0] in stay]
    yield rows
    yield plain_mix(rows)


def plain_mix(rows):
    """Sources by rounds of clamping and sharing again; documents in order of their hash up to the point nearest to the target."""
    sources = sorted({s for *_, s in rows}, key=lambda s: (s is None, s or ""))
    size = {r[0]: len(WORD.findall(r[1] or "")) for r in rows}
    total = {s: sum(size[r[0]] for r in rows if r[2] == s) for s in sources}
    weight = {s: (5, 2, 1)[k % 3] for k, s in enumerate(sources)}
    full, left = set(), 1.5 * sum(total.values())
    while True:
        share = left / max(1, sum(w for s, w in weight.items() if s not in full))
        over = {s for s in sources if s not in full and share * weight[s] > 2 * total[s]}
        if not over:
            break
        full |= over
        left = 1.5 * sum(total.values()) - sum(2 * total[s] for s in full)
    out = []
    for s in sources:
        target = 2 * total[s] if s in full else share * weight[s]
        whole = int(target // total[s]) if total[s] else 0
        rest, upto = target - whole * total[s], 0
        for r in sorted((r for r in rows if r[2] == s), key=lambda r: (hashlib.md5(f"17:{r[0]}".encode()).hexdigest()[:16], size[r[0]])):
            upto += size[r[0]]
            out += [r] * (whole + (rest > 0 and upto - size[r[0]] / 2 < rest))
    return out


def test_stages_equal_plain_versions(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    model = quality.train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    rows = [(r.doc_id, r.text, r.source) for r in docs.collect()]
    order = lambda x: sorted(x, key=str)
    for (_, stage), want in zip(corpus_pipeline.STAGES, plain_stages(model, rows)):
        docs = corpus_pipeline.materialize(stage(spark, docs, SF))
        assert order((r.doc_id, r.text, r.source) for r in docs.collect()) == order(want)
        assert all(r.n_chars == len(r.text or "") for r in docs.collect())
    enc, _ = bpe.tokenizer(open(public_tokenizers.path(queries.VOCABULARY), "rb").read(), public_tokenizers.PATTERN)
    ids = {i: enc.encode_ordinary(t or "") for i, t, _ in want}
    sha = lambda b: hashlib.sha256(b).hexdigest()
    want = order((i, len(ids[i]), sha(" ".join(map(str, ids[i])).encode()), sha((t or "").encode())) for i, t, _ in want)
    assert order(map(tuple, corpus_pipeline.run(spark, SF).collect())) == want


def test_stages_on_odd_rows(spark):
    """Nulls, repeated rows and ids, and columns with clashing names go through the whole chain."""
    good = spark.read.parquet(f"{SF}/documents.parquet").limit(40).collect()
    rows = [(r.doc_id, r.text, r.lang, r.source, r.n_chars, "mine", "own") for r in good]
    rows += [rows[0], rows[0], (None, rows[1][1], None, None, None, None, None), (rows[2][0], rows[3][1], "en", None, 5, "x", "y"), (None, None, None, None, None, None, None), (9_000, "", "en", "s", 0, "k", "w")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, score string, __key string")
    for name, stage in corpus_pipeline.STAGES:
        before, docs = docs, stage(spark, docs, SF)
        if name != "bpe_encoding":
            docs = corpus_pipeline.materialize(docs)
            assert docs.columns == before.columns
            if name != "line_dedup":
                assert docs.select("doc_id", "text", "score").distinct().exceptAll(before.select("doc_id", "text", "score").distinct()).count() == 0
    assert docs.count() > 0


def test_stages_on_no_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("false")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, SF).count() == 0


@pytest.mark.parametrize("name", list(queries.ORACLES))
def test_queries_equal_their_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings", "conversations"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = con.sql(queries.ORACLES[name])
    got = queries.QUERIES[name](spark, SF).select(*want.columns)
    assert sorted(map(str, map(tuple, got.collect()))) == sorted(map(str, want.fetchall()))
