"""The pipeline's stages against brute force on a small corpus, and its promises about rows and columns."""

import re
import zlib

import numpy as np
import pytest

import corpus_pipeline
from ivsearch.llm import quality_rules, tokens

WORD = re.compile(r"[^\x20\x09-\x0D]+")
R = np.random.default_rng(3)
VOCABULARY = ["river", "mill", "people", "town", "evening", "market", "bridge", "garden", "winter", "letter", "window", "summer", "teacher", "forest", "harbour", "music", "kitchen", "station", "doctor", "village"]


def prose(n):
    return " ".join(R.choice(VOCABULARY, n))


def junk(i):
    return " ".join(f"BUY!!! ${i} | CLICK!!! ${i * 3 + j} | WIN!!! FREE!!! CASH!!!" for j in range(8))


@pytest.fixture(scope="module")
def corpus(spark, tmp_path_factory):
    at = tmp_path_factory.mktemp("corpus")
    good = [prose(int(n)) for n in R.integers(60, 140, 160)]
    texts = {i: t for i, t in enumerate(good)} | {200 + i: junk(i) for i in range(80)}
    texts[300] = good[3] + "\n" + good[4]  # two lines that others have
    texts[301] = good[7].replace("river", "rivers", 1)  # a near copy of a whole text, and of a line if the rest is alike
    texts |= {400: None, 401: "", 402: " \n ", 403: "solo"}
    lang, source = (lambda i: "en" if i % 3 else None), (lambda i: f"s{i % 4}" if i % 5 else None)
    rows = [(i, t, lang(i), source(i), len(t or "")) for i, t in texts.items()]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(3).write.parquet(f"{at}/documents.parquet")
    spark.createDataFrame([(i, int(i < 200), 0) for i in texts if i < 300], "doc_id long, quality int, toxic int").write.parquet(f"{at}/labels.parquet")
    return str(at), texts


def test_stages(spark, corpus, tmp_path):
    at, texts = corpus
    docs = spark.read.parquet(f"{at}/documents.parquet")
    seen = []
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, at)
        if i < 4:
            assert out.columns == ["doc_id", "text", "lang", "source", "n_chars"], name
        out.write.parquet(str(tmp_path / str(i)))
        docs = spark.read.parquet(str(tmp_path / str(i)))
        seen.append(docs.collect())
    # The classifier rejects junk and keeps clean documents.
    kept = {r.doc_id for r in seen[0]}
    assert len([i for i in kept if 200 <= i < 280]) <= 4 and {i for i in texts if i < 160} <= kept
    # Exact lines stay once, at the smallest id.
    lines = [x for r in seen[1] for x in (r.text or "").split("\n") if WORD.search(x)]
    assert len(lines) == len(set(lines)) and all(r.n_chars == len(r.text) for r in seen[1] if r.text != texts.get(r.doc_id))
    by = {r.doc_id: r.text for r in seen[1]}
    assert 300 not in by or not WORD.search(by[300])
    # No two documents that stay share four fifths of their five-word shingles.
    sets = {}
    for r in seen[2]:
        w = [x.lower() for x in WORD.findall(r.text or "")]
        sets[r.doc_id] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set())
    ids = [i for i, s in sets.items() if s]
    assert all(len(sets[a] & sets[b]) * 10 < 8 * len(sets[a] | sets[b]) for a in ids for b in ids if a < b)
    assert {i for i in range(160)} <= set(sets)
    # The mix takes a share of 150% of all words, each source at most twice.
    words = lambda rows: sum(len(WORD.findall(r.text or "")) for r in rows)
    for s in {r.source for r in seen[2]}:
        own = words([r for r in seen[2] if r.source == s])
        assert words([r for r in seen[3] if r.source == s]) <= 2 * own
    assert abs(words(seen[3]) - 1.5 * words(seen[2])) <= 0.01 * words(seen[2]) + 5 * len({r.source for r in seen[2]})
    # Every id of every mixed document lies in one piece, and no window holds more than 1,024.
    enc, windows, n = tokens.encoder(tokens.vocabulary()), {}, 0
    for r in seen[4]:
        windows[r.sequence_id] = windows.get(r.sequence_id, 0) + r.length
        n += r.length
        assert r.ids_crc32 == zlib.crc32(np.array(r.ids, "<u4").tobytes())
    assert max(windows.values()) <= 1024 and n == sum(len(enc.ids(r.text)) // 4 + 1 for r in seen[3])


def test_run_is_its_stages(spark, corpus):
    at, _ = corpus
    out = corpus_pipeline.run(spark, at)
    assert out.count() > 0 and {"doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"} <= set(out.columns)


def test_no_rows(spark, corpus, tmp_path):
    at, _ = corpus
    for t in ("documents", "labels"):
        spark.read.parquet(f"{at}/{t}.parquet").limit(0).write.parquet(str(tmp_path / f"{t}.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_kept_by_brute_force(spark):
    """op10's verdict on a small table: cutoffs from the exact binomial tail, by score, rule and stratum."""
    from math import comb

    texts = [" ".join(R.choice(VOCABULARY, 60)) + " #" * int(k) for k in np.minimum(R.zipf(1.6, 900), 40)]
    rows = [(i, t, "en" if i % 2 else "de") for i, t in enumerate(texts)]
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    good = {i for i in range(900) if i % 9}
    labels = spark.createDataFrame([(i, int(i in good)) for i in range(900)], "doc_id long, quality int")
    alpha, delta = 0.02, 0.05
    measured = quality_rules.measures(d).withColumns(quality_rules.scores())
    score = {r.doc_id: r for r in measured.collect()}
    base = {i for i, r in score.items() if r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words}

    def allowed(n):
        tail, k = 0.0, None
        for i in range(n + 1):
            tail += comb(n, i) * alpha**i * (1 - alpha) ** (n - i)
            if tail > delta / len(quality_rules.RULES) / 2:
                return k
            k = i
        return k

    cut = {}
    for lang in ("en", "de"):
        own = [score[i] for i in good - base if rows[i][2] == lang]
        most = allowed(len(own))
        for rule in quality_rules.RULES:
            fits = [s for s in {r[rule] for r in own} if most is not None and sum(r[rule] > s for r in own) <= most]
            cut[lang, rule] = min(fits, default=10**9)
    want = {i for i, r in score.items() if i not in base and all(r[rule] <= cut[rows[i][2], rule] for rule in quality_rules.RULES)}
    got = {r.doc_id for r in quality_rules.judge(d, labels, alpha, delta).where("kept").collect()}
    assert got == want and len(want) < 900 - len(base)
