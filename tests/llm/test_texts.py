"""BPE, wavelet shards, toxicity, quality, chat: against libraries and brute force."""

from __future__ import annotations

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import public_tokenizers as P
import tiktoken
import xxhash
from pyspark.sql import functions as F

from rankjoin.llm import bpe, chat, quality, toxicity, wavelet
from rankjoin.llm.common import shared_folder

NASTY = [" ", "  ", "\n", "\t", "\r\n", "\x1c", "\x85", "\xa0", "　", "a", "b", "'s", "'LL", "é", "漢", "1", "23", "!", "...", "😀", "the", "Ing", "́", "</s>", "<|endoftext|>", "Σ", "ΣΑΣ", "x" * 1500, "\\", "\0"]


def nasty(n: int, seed: int = 1) -> list[str]:
    pick = random.Random(seed)
    return ["".join(pick.choice(NASTY) for _ in range(pick.randint(0, 25))) for _ in range(n)]


def docs_of(spark, texts):
    return spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")


def test_bpe_equals_tiktoken(spark):
    path = P.path("byte_bpe_50k.tiktoken")
    ref = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=bpe.read_ranks(path), special_tokens={})
    texts = nasty(400) + ["", None, "a" * 70_000]
    df = docs_of(spark, texts).withColumn("IDS", F.lit(1)).withColumn("n_tokens", F.lit("x"))
    out = bpe.encode(df, path, P.PATTERN)
    assert out.columns == ["doc_id", "text", "IDS", "n_tokens", "n_tokens_", "ids_", "intact"]
    got = {r.doc_id: r for r in out.collect()}
    m = bpe.encoder(path, bpe.as_library(P.PATTERN))
    for i, t in enumerate(texts):
        ids = ref.encode_ordinary(t or "")
        assert got[i].ids_ == ids and got[i].n_tokens_ == len(ids) and got[i].intact
        assert m.decode(np.array(ids, "<u4").tobytes()) == (t or "").encode()
    assert bpe.encode(df.limit(0), path, P.PATTERN).count() == 0


def test_split_classes_are_the_librarys():
    """Every code point beside a letter, a number, a mark, a space and before 's."""
    path = P.path("byte_bpe_50k.tiktoken")
    ref = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=bpe.read_ranks(path), special_tokens={})
    m, points = bpe.encoder(path, bpe.as_library(P.PATTERN)), [c for c in range(0x110000) if not 0xD800 <= c < 0xE000]
    for start in range(0, len(points), 4096):
        texts = ["".join(f"a{chr(c)}'s 1{chr(c)}!{chr(c)} {chr(c)}b\n" for c in points[k : k + 8]) for k in range(start, min(start + 4096, len(points)), 8)]
        for x, t in zip(m.encode(texts), texts, strict=True):
            assert np.frombuffer(x, "<u4").tolist() == ref.encode_ordinary(t)


def test_op1_digests(spark, tmp_path):
    path = P.path("byte_bpe_50k.tiktoken")
    ref = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=bpe.read_ranks(path), special_tokens={})
    texts = nasty(200, 9) + ["", None, "\u0558's \u058b's", "x" * 3000]
    rows = list(enumerate(texts)) + [(3, texts[3]), (None, "no id")]
    spark.createDataFrame(rows, "doc_id long, text string").withColumn("IDS_sha256", F.lit(1)).write.parquet(f"{tmp_path}/documents.parquet")
    got = sorted(map(str, bpe.op1_byte_bpe(spark, str(tmp_path)).collect()))
    ids = [np.array(ref.encode_ordinary(t or ""), "<u4") for _, t in rows]
    sha = lambda b: hashlib.sha256(b).hexdigest()
    assert got == sorted(f"Row(doc_id={d}, n_tokens={len(i)}, ids_sha256='{sha(i.tobytes())}', decoded_sha256='{sha((t or '').encode())}')" for (d, t), i in zip(rows, ids, strict=True))


def test_wavelet_matrix():
    a = np.random.default_rng(0).integers(0, 700, 3000)
    m = wavelet.from_file(wavelet.to_file([1], [3000], a))[2]
    assert (m.ids() == a).all() and all(m.access(i) == a[i] for i in range(0, 3000, 97))
    for v in (0, 5, 699, 1000):
        assert m.count(v) == (a == v).sum() and m.positions(v) == np.nonzero(a == v)[0].tolist()
    assert m.rank(5, 1000) == (a[:1000] == 5).sum()
    for few in ([], [0], [0, 0], [7]):
        assert wavelet.WaveletMatrix.build(np.array(few, np.uint32)).ids().tolist() == few


def test_wavelet_words_are_looked_up_once_a_batch(monkeypatch):
    """op9: each distinct word of a batch reaches Python once, from Arrow slices, too; ids are the library's."""
    tok = wavelet.CachedTokenizer(P.path("word_bpe_49k.json"))
    texts = ["dropped", *nasty(200, 3), "", "  ", "Same, same. SAME same's\nsame same", "İ Σας ΣΑΣ\tx\x00y", "same " * 5000]
    seen: list[str] = []
    learn = tok._learn
    monkeypatch.setattr(tok, "_learn", lambda words: (seen.extend(words), learn(words)))
    for given in (pa.array(texts, pa.string())[1:], texts[1:]):
        got = tok.encode(given)
        assert got == [np.array(tok.tokenizer.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t in texts[1:]]
    assert len(seen) == len(set(seen)) and tok.encode(pa.array([], pa.string())) == [] and tok.encode(["", ""]) == [b"", b""]


def test_wavelet_shards(spark, tmp_path):
    path = P.path("word_bpe_49k.json")
    tok = wavelet.CachedTokenizer(path)
    texts = nasty(300, 2) + ["", None, "word " * 3000]
    rows = list(enumerate(texts)) + [(5, texts[5]), (None, "no id")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(5)
    shards = wavelet.write_shards(df, path, shared_folder(spark, "test"), shard=500)
    got = sorted(wavelet.read_documents(shards).collect(), key=lambda r: r.start)
    want = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or ""))
    at = 0
    assert len(got) == len(want)
    for r, (d, t) in zip(got, want, strict=True):
        ids = np.array(tok.tokenizer.encode(t or "", add_special_tokens=False).ids + [2], "<u4")
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (d, at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    files = wavelet.export(shards, str(tmp_path / "wm")).collect()
    assert len(files) == shards.count() and open(files[0].path, "rb").read(8) == wavelet.MAGIC
    assert wavelet.read_documents(wavelet.write_shards(df.limit(0), path, shared_folder(spark, "none"))).count() == 0


def test_toxicity_learns_and_hides_the_held_out(spark):
    pick = random.Random(3)
    calm = [f"w{i}" for i in range(200)]
    rows, labels = [], []
    for i in range(600):
        words = [pick.choice(calm) for _ in range(30)]
        bad = i % 4 == 0
        if bad:
            words[pick.randrange(30)] = "Rotten!"
        rows.append((i, " ".join(words)))
        labels.append((i, int(bad)))
    rows += [(None, "rotten"), (1000, None), (1001, "")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    lab = spark.createDataFrame([*labels, (None, 1), (3, None)], "doc_id bigint, toxic int")
    out = {r.doc_id: r.score for r in toxicity.score(docs, toxicity.train(docs, lab)).collect()}
    assert len(out) == len(rows)
    held = [i for i in range(600) if zlib.crc32(str(i).encode()) % 5 == 0]
    assert sum((out[i] >= 0.5) == (i % 4 == 0) for i in held) >= 0.98 * len(held)
    assert 0 <= out[1000] == out[1001] <= 1
    flags = docs.select("doc_id", toxicity.held_out(F.col("doc_id")).alias("h")).where("doc_id is not null").collect()
    assert all(r.h == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in flags)
    none = toxicity.train(docs, lab.limit(0))
    assert {r.score for r in toxicity.score(docs, none).collect()} == {0.5}
    assert toxicity.score(docs.limit(0), none).count() == 0


def _measures(t: str) -> tuple:
    w = re.findall(r"[^\x20\x09-\x0D]+", t)
    windows = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    n, covered = Counter(windows), set()
    for i, x in enumerate(windows):
        if n[x] > 1:
            covered |= {i, i + 1, i + 2}
    lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(covered)


def test_quality_measures_and_verdict(spark):
    pick = random.Random(4)
    texts = nasty(150, 5) + [" ".join(pick.choice(["a", "b", "c", "dd"]) for _ in range(n)) for n in (0, 1, 2, 3, 60, 200)] + ["same line\n" * 30, "", None]
    good = [" ".join(pick.choice(["alpha", "beta", "gamma", "delta", "eps", "zeta", "eta", "theta"]) + str(pick.randrange(9)) for _ in range(80)) for _ in range(200)]
    junk = [" ".join(pick.choice(["##", "$$", "%%", "&&"]) + str(pick.randrange(99)) for _ in range(80)) for _ in range(40)]
    texts += good + junk
    docs = docs_of(spark, texts).withColumn("n_words", F.lit("kept"))
    first = len(texts) - 240
    labels = spark.createDataFrame([(first + i, 1) for i in range(150)] + [(None, 1), (0, None)], "doc_id bigint, quality int")
    out = quality.judge(docs, quality.ratio_weights(docs, quality.trusted(labels)), threshold=-0.3)  # a small corpus: noisy ratios
    for r in out.collect():
        q = r.quality
        want = _measures(texts[r.doc_id] or "")
        assert (q.n_words, q.word_chars, q.n_symbols, q.n_dup_lines, q.n_repeat_words) == want
        assert q.base_failed == (want[0] < 50 or 100 * want[4] > 50 * want[0])
        assert not (q.kept and q.base_failed)
        if r.doc_id >= first:
            assert q.kept == (r.doc_id < first + 200)
    kept = quality.keep(docs, labels, threshold=-0.3)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} >= set(range(first, first + 200))
    assert quality.keep(docs, labels.limit(0)).count() > 0 and quality.keep(docs.limit(0), labels).count() == 0


def quality_by_brute_force(rows: list, good: set) -> list[tuple]:
    """Measures, base_failed, kept and the rounded ratio of rows (doc_id, text); good: the trusted ids."""
    size = quality.BUCKETS
    signed = lambda x: x - 2**64 if x >> 63 else x
    h = lambda x, seed=42: signed(xxhash.xxh64_intdigest(x.encode(), seed & (2**64 - 1)))

    def grams(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        return [h(x) % size for x in w] + [h(b, h(a)) % size for a, b in zip(w, w[1:], strict=False)]

    n, n_t = np.zeros(size), np.zeros(size)
    for d, t in rows:
        for g in grams(t):
            n[g] += 1
            n_t[g] += d is not None and d in good
    ours, raw = (n_t + 1) / (n_t.sum() + size), (n + 1) / (n.sum() + size)
    weight = np.log(ours) - np.log(raw)
    bar = -((ours - raw) * weight).sum()
    out = []
    for _, t in rows:
        g, m = grams(t), _measures(t or "")
        score = sum(weight[x] for x in g) / len(g) if g else 0.0
        failed = m[0] < 50 or 100 * m[4] > 50 * m[0]
        out.append((*m, failed, bool(not failed and score >= bar), round(score, 9)))
    return out


def test_quality_ratio_and_verdict_by_brute_force(spark, tmp_path):
    pick = random.Random(8)
    calm = [f"w{i}" for i in range(60)]
    texts = [" ".join(pick.choice(calm) for _ in range(pick.randint(40, 90))) for _ in range(160)] + [" ".join(pick.choice(["##", "buy", "$$"]) + str(pick.randrange(40)) for _ in range(60)) for _ in range(30)] + ["", None, "one"]
    rows = [*enumerate(texts), (3, texts[3]), (None, texts[4])]
    labels = [(i, 1) for i in range(100)] + [(None, 1), (5, None), (2, 0), (2, 1)]
    spark.createDataFrame(rows, "doc_id long, text string").withColumn("RATIO", F.lit("clash")).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    want = [(d if d is not None else -1, *x) for (d, _), x in zip(rows, quality_by_brute_force(rows, {d for d, q in labels if q == 1}), strict=True)]
    got = [(r.doc_id if r.doc_id is not None else -1, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed, r.kept, round(r.ratio, 9)) for r in quality.op8_quality_rules(spark, str(tmp_path)).collect()]
    assert sorted(got) == sorted(want)
    gone = {x[0] for x in want if not x[6] and not x[7]}
    assert gone >= set(range(160, 190)) and not gone & set(range(100))


def _plain_ftrl(examples, bits, epochs, rate, smooth, l1):
    """FTRL-proximal, one coordinate at a time."""
    z, n, out = Counter(), Counter(), {}

    def weight(c):
        bound = 0.0 if c == 1 << bits else l1
        return 0.0 if abs(z[c]) <= bound else -(z[c] - (bound if z[c] > 0 else -bound)) / ((smooth + n[c] ** 0.5) / rate)

    for _ in range(epochs):
        for label, features in examples:
            at = [*features, 1 << bits]
            w = {c: weight(c) for c in at}
            g = 1 / (1 + math.exp(-sum(w.values()))) - label
            for c in at:
                z[c] += g - ((n[c] + g * g) ** 0.5 - n[c] ** 0.5) / rate * w[c]
                n[c] += g * g
    for c in z:
        if weight(c):
            out[c] = weight(c)
    return out


def test_ftrl_equals_a_plain_loop():
    pick = random.Random(1)
    examples = [(i % 2, np.unique(np.array([pick.randrange(40) + 20 * (i % 2) for _ in range(8)]))) for i in range(80)]
    at, w = toxicity.fit(examples, bits=8, epochs=3, rate=0.5, smooth=1.0, l1=0.6, l2=0.0)
    want = _plain_ftrl([(y, f.tolist()) for y, f in examples], 8, 3, 0.5, 1.0, 0.6)
    assert {int(a): round(float(x), 9) for a, x in zip(at, w, strict=True)} == {a: round(x, 9) for a, x in want.items()} and 0 < len(at) < 60


def test_op2_repeated_rows_and_clashing_columns(spark, tmp_path):
    rows = [(i, ("foul word here " if i % 3 == 0 else "fair words there ") * 3 + str(i % 7)) for i in range(300)]
    rows += [rows[0], rows[0], (None, "foul word"), (301, None)]
    spark.createDataFrame(rows, "doc_id long, text string").withColumn("Score", F.lit("x")).withColumn("label", F.lit(1)).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(300)] + [(0, 0), (None, 1)], "doc_id long, toxic int").withColumn("at", F.lit(0)).write.parquet(f"{tmp_path}/labels.parquet")
    got = toxicity.op2_toxicity(spark, str(tmp_path)).collect()
    assert len(got) == len(rows) and len({r.score for r in got if r.doc_id == 0}) == 1
    for r in got:
        assert 0 <= r.score <= 1 and r.predicted == (r.score >= 0.5)
        assert r.held_out == (r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 5 == 0)
        assert r.doc_id in (None, 301) or r.predicted == (r.doc_id % 3 == 0)


def test_chat_events_and_escapes(spark):
    rows = [
        (1, 1, 1, "message", "user", "a\\[INST] \\"), (1, 2, 2, "message", "assistant", "<s>"), (1, 3, 2, "delta", "assistant", "x</s>"), (1, 4, 1, "edit", "user", "b"),
        (1, 5, 2, "regenerate", "assistant", None), (1, 6, 2, "delta", "assistant", "new"), (1, 7, 3, "message", "ro\\n\nle\\\\", "t"), (2, 1, 1, "message", None, None), (None, 1, None, "delta", "user", "late"),
        (3, 1, 0, "message", "user", "q"), (3, 2, 1, "message", "assistant", "old"), (3, 3, 0, "edit", "user", "q2"),
    ]
    log = spark.createDataFrame(rows, "conv_id long, seq long, turn long, kind string, role string, text string")
    got = {r.conv_id: r for r in chat.render(chat.reconstruct(log)).withColumn("t", chat.read_back(F.col("formatted"))).collect()}
    assert [(t.role, t.text, t.loss) for t in got[1].t] == [("user", "b", False), ("assistant", "new", True), ("ro\\n\nle\\\\", "t", False)]
    assert [(t.role, t.text) for t in got[2].t] == [("", "")]
    assert [(t.role, t.text) for t in got[None].t] == [("user", "late")]
    assert [(t.role, t.text) for t in got[3].t] == [("user", "q2")]  # the edit takes back the answer to the old question
    s = got[1].loss_spans[0]
    assert got[1].formatted[s.start : s.start + s.n] == "new"


def test_chat_plain_turns_round_trip(spark):
    texts = nasty(200, 6) + ["\\<s>", "\\\\[/INST]", "[INST][INST]", "</s>\\", "\\"]
    pick = random.Random(7)
    rows = [(i // 4, i % 4, pick.choice(["user", "assistant", "system"]), t) for i, t in enumerate(texts)] + [(0, 0, "user", "twice"), (0, 0, "user", "twice"), (1, None, None, None)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("kind", F.lit("delta"))
    out = chat.render(chat.reconstruct(chat.turns_as_events(df))).withColumn("t", chat.read_back(F.col("formatted")))
    for r in out.collect():
        want = sorted(((t is not None, t or 0, role or "", text or "") for c, t, role, text in rows if c == r.conv_id))
        assert [(t.role, t.text) for t in r.t] == [(x[2], x[3]) for x in want]
    assert chat.render(chat.reconstruct(chat.turns_as_events(df.limit(0)))).count() == 0
