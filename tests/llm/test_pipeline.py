"""The pipeline: every stage, on what the one before it kept, against brute force."""

from __future__ import annotations

import random

import numpy as np
import public_tokenizers as P
import tiktoken
from pyspark.sql import functions as F
from test_corpus import copies_by_brute_force, dropped_by_brute_force, groups_by_brute_force
from test_texts import quality_by_brute_force

from rankjoin.llm import bpe

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars", "ROW"]


def corpus() -> tuple[list, list]:
    """Rows of documents and labels: prose, junk, shared lines, exact and near copies, repeated rows, nulls."""
    pick = random.Random(12)
    calm = [f"word{i}" for i in range(90)]
    prose = lambda n: [pick.choice(calm) for _ in range(n)]
    texts = []
    for _ in range(60):
        w = prose(pick.randint(60, 120))
        texts.append(" ".join(w[:20]) + "\n" + " ".join(w[20:]))
    texts += [" ".join(pick.choice(["##", "buy", "$$"]) + str(pick.randrange(40)) for _ in range(70)) for _ in range(12)]
    for t in texts[:12]:  # near copies: one word of many
        w = t.replace("\n", " ").split()
        w[pick.randrange(len(w))] = "changed"
        texts.append(" ".join(w))
    shared = "This line stands in many of the documents, number "
    texts += [f"{shared}{i}\n" + " ".join(prose(70)) for i in range(10)] + texts[3:6] + ["", None, "too short"]
    rows = [(i, t) for i, t in enumerate(texts)]
    rows += [(200, texts[20]), (None, " ".join(prose(80)))]
    return [(d, t, "en", pick.choice(["web", "book", None]), len(t or ""), "x") for d, t in rows], [(i, int(not 60 <= i < 72)) for i in range(0, 90)]


def test_every_stage_against_brute_force(spark, tmp_path):
    import corpus_pipeline as pipeline

    given, labels = corpus()
    spark.createDataFrame(given, "doc_id long, text string, lang string, source string, n_chars long, ROW string").repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    key = lambda r: tuple((x is not None, x) for x in r)
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")

    def after(n: int) -> list:
        nonlocal docs
        pipeline.STAGES[n][1](spark, docs, str(tmp_path)).write.parquet(f"{tmp_path}/{n}")
        docs = spark.read.parquet(f"{tmp_path}/{n}")
        assert docs.columns[:6] == COLUMNS and (n == 4 or docs.columns == COLUMNS)
        return sorted(map(tuple, docs.select(*COLUMNS).collect()), key=key)

    rows = [r for r, q in zip(given, quality_by_brute_force([r[:2] for r in given], {d for d, q in labels if q}), strict=True) if q[6]]
    assert 60 < len(rows) < len(given) and after(0) == sorted(rows, key=key)

    kept = []
    for r, gone in zip(rows, dropped_by_brute_force([r[:2] for r in rows]), strict=True):
        text = "\n".join(x for i, x in enumerate(r[1].split("\n")) if i not in gone)
        kept.append((r[0], text, r[2], r[3], len(text), r[5]))
    rows = kept
    assert after(1) == sorted(rows, key=key)

    rows.sort(key=lambda r: (r[0] is None, r[0] or 0))
    before, roots = len(rows), groups_by_brute_force([r[1] for r in rows])
    rows = [r for k, r in enumerate(rows) if roots[k] == k]
    assert len(rows) < before - 5 and after(2) == sorted(rows, key=key)

    rows = [r for r, n in zip(rows, copies_by_brute_force([(r[0], r[1], r[3]) for r in rows]), strict=True) for _ in range(n)]
    assert after(3) == sorted(rows, key=key)

    assert after(4) == sorted(rows, key=key)
    ref = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=bpe.read_ranks(P.path("byte_bpe_50k.tiktoken")), special_tokens={})
    for r in docs.collect():
        assert r.ids == ref.encode_ordinary(r.text) and r.n_tokens == len(r.ids) and r.intact


def test_run_on_the_given_tables_and_on_empty_ones(spark, sf):
    import corpus_pipeline as pipeline

    out = pipeline.run(spark, sf)
    assert out.count() > 0 and out.where(~F.col("intact")).isEmpty()
    nothing = spark.read.parquet(f"{sf}/documents.parquet").limit(0)
    for _, stage in pipeline.STAGES:
        assert stage(spark, nothing, sf).count() == 0
    assert np.all([callable(f) for _, f in pipeline.STAGES])
