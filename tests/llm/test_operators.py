"""The training-data operators against brute force, on small tables with nulls, empty texts, ties, repeats and clashing columns."""

import re
import zlib

import numpy as np
import pyarrow as pa
import pytest

from ivsearch.llm import graph_ann, language_id, line_dedup, mixing, ngram_join, packing, quality_classifier, quality_rules, sharding, token_files, tokens

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ROWS = [(i, t, "en" if i % 3 else None, f"s{i % 4}" if i % 5 else None, 7) for i, t in enumerate(
    [None, "", " ", "one two three four five six", "one two three four five six", "the quick brown fox jumps over the lazy dog again and again\nthe quick brown fox jumps over the lazy dog again and agaim", "x " * 3000, "a\nb\na\n\nb", "日本 語 テスト", "the quick brown fox jumps over the lazy dog again and again"] * 2)]
DDL = "doc_id long, text string, lang string, source string, size int"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([*ROWS, (None, "no id here at all", None, None, 1), ROWS[5]], DDL)


def lev(a, b):
    p = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        q = [i]
        for j, y in enumerate(b, 1):
            q.append(min(p[j] + 1, q[-1] + 1, p[j - 1] + (x != y)))
        p = q
    return p[-1]


def test_lines(docs):
    first, got = {}, {(r.doc_id, r.text, r.n_lines, r.n_near) for r in line_dedup.dedup_lines(docs, 2, 20).collect()}
    rows = [(2**63 - 1 if r.doc_id is None else r.doc_id, r.text) for r in docs.collect()]
    for d, t in sorted(rows, key=lambda r: r[0]):
        for p, x in enumerate(t.split("\n") if t is not None else []):
            if WORD.search(x) and (x not in first or (d, p) < first[x]):
                first[x] = (d, p)
    near = {b for b in first if len(b) >= 20 and any(len(a) >= 20 and first[a] < first[b] and abs(len(a) - len(b)) < 3 and lev(a, b) <= 2 for a in first)}
    want = set()
    for d, t in rows:
        ls = t.split("\n") if t is not None else []
        kept = [x for p, x in enumerate(ls) if not WORD.search(x) or (first[x] == (d, p) and x not in near)]
        want.add((None if d == 2**63 - 1 else d, None if t is None else "\n".join(kept), len(ls), sum(1 for p, x in enumerate(ls) if first.get(x) == (d, p) and x in near)))
    assert got == want


def test_lines_of_rows_without_id(spark):
    a, b, c = "the first line that the others resemble here", "a line of a row without id, all its own", "another line of another row without id"
    rows = [(1, a, 1), (None, f"{a[:-1]}m\n{b}", 2), (None, f"{c}\nand its second line", 3), *[(None, "copied line of rows without id\nx", 4)] * 3, (7, f"{b[:9]} and something else instead\ny", 5), (7, f"{a}\nz\na line of the other row of id 7", 6), (None, None, 7), (None, None, 7)]
    got = sorted((r.n, r.text or "", r.n_lines, r.n_copies, r.n_near) for r in line_dedup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string, n int").repartition(3), 2, 20).collect())
    assert got == sorted([
        (1, a, 1, 0, 0), (2, b, 2, 0, 1), (3, f"{c}\nand its second line", 2, 0, 0), (4, "copied line of rows without id\nx", 2, 0, 0), (4, "", 2, 2, 0), (4, "", 2, 2, 0),
        (5, f"{b[:9]} and something else instead\ny", 2, 0, 0), (6, "z\na line of the other row of id 7", 3, 1, 0), (7, "", 0, 0, 0), (7, "", 0, 0, 0),
    ])


def test_lines_group(spark):
    """A group of variants of one line, 0 to 6 edits each, against brute force; columns named like internal ones pass through."""
    rng = np.random.default_rng(5)
    base = "the mill by the river was built long before the town had its first school and é church"
    made = []
    for i in range(90):
        x = list(base)
        for _ in range(i % 7):
            at = int(rng.integers(0, len(x)))
            x[at : at + int(rng.integers(0, 2))] = str(rng.choice(list("aeñ "))) if rng.integers(0, 3) else ""
        made.append("".join(x))
    rows = [(i, made[i], f"k{i}", i, "w", [i]) for i in rng.permutation(90).tolist()]
    got = {r.doc_id: r for r in line_dedup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string, _l string, keep int, row string, d array<int>").repartition(4), 2, 20).collect()}
    for i, x in enumerate(made):
        copy, near = x in made[:i], any(lev(x, y) <= 2 for y in made[:i])
        assert (got[i].n_copies, got[i].n_near, got[i].text) == (int(copy), int(near and not copy), "" if near else x)
        assert (got[i]._l, got[i].keep, got[i].row, got[i].d) == (f"k{i}", i, "w", [i])
    assert line_dedup.dedup_lines(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def classes(rows, num, den, n):
    sets = {}
    for d, t in sorted((d, t or "") for d, t in rows if d is not None):
        w = [x.lower() for x in WORD.findall(t)]
        sets.setdefault(d, {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set()))
    up = {d: d for d in sets}

    def top(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in sets:
        for b in sets:
            both = len(sets[a] & sets[b])
            if a < b and both and den * both >= num * (len(sets[a]) + len(sets[b]) - both):
                x, y = top(a), top(b)
                up[max(x, y)] = min(x, y)
    return {(d, len(s), top(d)) for d, s in sets.items()}


def test_jaccard(spark, docs):
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    assert {tuple(r) for r in ngram_join.jaccard_classes(docs, 9, 10, 3).collect()} == classes(rows, 9, 10, 3)
    rng = np.random.default_rng(2)
    base = [rng.integers(0, 25, 18) for _ in range(8)]
    more = []
    for i in range(120):
        x = base[i % 8].copy()
        x[rng.integers(0, 18, rng.integers(0, 3))] = rng.integers(0, 25)
        more.append((i * 7 % 121, " ".join(f"W{w}" for w in x)))
    assert {tuple(r) for r in ngram_join.jaccard_classes(spark.createDataFrame(more, "doc_id long, text string"), 6, 10, 2).collect()} == classes(more, 6, 10, 2)


def test_jaccard_repeated_ids(spark):
    a, b = " ".join(f"a{i}" for i in range(40)), " ".join(f"b{i}" for i in range(40))
    d = spark.createDataFrame([(1, a, 0), (1, b, 1), (2, b, 2), (3, a, 3), (3, a, 3), (None, a, 4), (4, None, 5)], "doc_id long, text string, rep int")
    assert sorted(tuple(r) for r in ngram_join.jaccard_classes(d, 9, 10, 3).collect()) == [(1, 38, 1), (2, 38, 2), (3, 38, 1), (4, 0, 4)]
    assert sorted((r.doc_id or 0, r.rep) for r in ngram_join.drop_near_copies(d).collect()) == [(0, 4), (1, 0), (1, 1), (2, 2), (4, 5)]
    assert ngram_join.jaccard_classes(d.limit(0)).count() == 0


def test_jaccard_group(spark):
    """Variants of one long text, most pairs of them just under the threshold, some sharing changes."""
    rng = np.random.default_rng(8)
    rows = []
    for i in range(150):
        w = [f"w{j}" for j in range(120)]
        for _ in range(i % 9):
            w[rng.integers(0, 120)] = f"x{rng.integers(0, 12)}"
        rows.append((int(i), " ".join(w[: 120 - i % 4])))
    assert {tuple(r) for r in ngram_join.jaccard_classes(spark.createDataFrame(rows, "doc_id long, text string"), 9, 10, 3).collect()} == classes(rows, 9, 10, 3)


def test_jaccard_crowd(spark, monkeypatch):
    """A large group of near copies, of which some pairs are linked, leaves few pairs for the second step."""
    rng, rows, left = np.random.default_rng(4), [], {}
    for i in range(400):
        w = [f"w{j}" for j in range(200)]
        for at in rng.choice(200, 1 + i % 4, replace=False):
            w[at] = f"x{rng.integers(0, 10**6)}"
        rows.append((i, " ".join(w)))
    stage = ngram_join.stage

    def counted(df, name="t"):
        out = stage(df, name)
        left[name] = out.count() if name in ("pivots", "open") else 0
        return out

    monkeypatch.setattr(ngram_join, "stage", counted)
    got = {tuple(r) for r in ngram_join.jaccard_classes(spark.createDataFrame(rows, "doc_id long, text string"), 9, 10, 3).collect()}
    assert got == classes(rows, 9, 10, 3)
    assert left["pivots"] <= 400 and left["open"] <= 1600, left


def test_jaccard_few(spark, monkeypatch):
    """Few links are joined by one task, not by rounds of shuffles; many give the same components, and larger joins the same rows."""
    rng = np.random.default_rng(12)
    a, b = rng.integers(0, 3000, (2, 1500))
    a[:40], b[:40] = np.arange(5000, 5040), np.arange(5001, 5041)
    edges, names, stage = spark.createDataFrame(list(zip(a.tolist(), b.tolist())), "a long, b long").where("a <> b"), [], ngram_join.stage
    monkeypatch.setattr(ngram_join, "stage", lambda df, name="t": names.append(name) or stage(df, name))
    one = {tuple(r) for r in ngram_join.components(edges).collect()}
    assert names == [] and ngram_join.components(edges.limit(0)).count() == 0
    rows = [(i, " ".join(f"w{j}" if j != 7 * i % 90 else f"x{i % 5}" for j in range(90))) for i in range(60)]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    few = {tuple(r) for r in ngram_join.jaccard_classes(d, 9, 10, 3).collect()}
    assert "edges" not in names and few == classes(rows, 9, 10, 3)
    monkeypatch.setattr(ngram_join, "FEW", 0)
    monkeypatch.setattr(ngram_join, "lit", lambda df, rows, few=0: df)
    monkeypatch.setattr(ngram_join, "fit", lambda df, rows: df)
    assert {tuple(r) for r in ngram_join.components(edges).collect()} == one and names.count("edges") > 2
    assert {tuple(r) for r in ngram_join.jaccard_classes(d, 9, 10, 3).collect()} == few


def test_packing(docs):
    enc = tokens.encoder(tokens.vocabulary())
    seen, windows = {}, {}
    for r in packing.pack(docs).collect():
        assert zlib.crc32(np.array(r.ids, "<u4").tobytes()) == r.ids_crc32
        seen.setdefault(r.doc_id, []).append((r.start, r.ids))
        windows.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for d, t, *_ in ROWS:
        if d != 5:
            assert [x for _, ids in sorted(seen[d]) for x in ids] == np.frombuffer(enc.ids(t), "<u4").tolist() + [0]
    for w in windows.values():
        ends = np.cumsum([0] + [n for _, n in sorted(w)])
        assert [o for o, _ in sorted(w)] == ends[:-1].tolist() and ends[-1] <= 1024
    parts = packing.windows(list(range(1, 400)), 1024)
    assert sorted(i for p in parts for i in p) == list(range(399)) and len(parts) <= 84


def test_mixing(docs):
    got = mixing.plan(docs).collect()
    assert len(got) == docs.count() and "size" in mixing.plan(docs).columns
    by = {}
    for r in got:
        taken = r.whole * r.size + r.part
        assert taken <= 2 * r.size
        by.setdefault(r.source, [r.target, 0])[1] += taken
    assert all(abs(t - x) <= 1 + 20 for t, x in by.values())
    words = sum(len(WORD.findall(r.text or "")) for r in mixing.mix(docs).collect())
    assert abs(words - sum(x for _, x in by.values())) == 0
    assert mixing.plan(docs.limit(0)).count() == 0


def test_mixing_repeats(spark):
    rows = [(i, f"{i} " + "word " * (i % 37 + 5), f"s{i % 5}") for i in range(60) for _ in range(2)] + [(None, "no id and the same text", "n")] * 9 + [(None, "no id, " + "own text " * i, None) for i in range(9)] * 3
    d = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(5)
    got, by = mixing.plan(d).collect(), {}
    assert sorted((r.doc_id or -1, r.text, r.source or "") for r in got) == sorted((i or -1, t, s or "") for i, t, s in rows)
    for r in got:
        assert 0 <= r.part <= r.size
        by.setdefault(r.source, [int(r.target + 0.5), 0])[1] += r.whole * r.size + r.part
    assert len(by) == 7 and all(t == x for t, x in by.values())
    words = {}
    for r in mixing.mix(d).collect():
        words[r.source] = words.get(r.source, 0) + len(WORD.findall(r.text))
    assert words == {s: x for s, (_, x) in by.items()}


def test_clashing_columns(spark):
    """Columns named like those that operators use inside pass through unchanged, nulls and repeated rows too."""
    names = ["row", "key", "bucket", "cut", "q", "whole_", "k", "f", "s", "n", "first", "h", "w", "t", "_id", "_key", "_k", "_l", "weight", "cut_bucket", "left", "at"]
    rows = [(i if i % 4 else None, f"text number {i // 2} " * (i % 5) if i % 7 else None, f"s{i % 2}", "en", *range(len(names))) for i in range(30)]
    d = spark.createDataFrame(rows, "doc_id long, text string, source string, lang string, " + ", ".join(f"`{n}` int" for n in names))
    own = sorted(map(repr, rows))
    same = lambda df: sorted(repr(tuple(r)) for r in df.select(*[f"`{c}`" for c in d.columns]).collect())
    assert same(mixing.plan(d)) == own and same(sharding.shard(d, 3)) == own and same(quality_rules.measures(d)) == own
    assert set(mixing.mix(d).columns) == set(d.columns) and mixing.mix(d).select("weight").distinct().count() == 1
    assert set(same(ngram_join.drop_near_copies(d))) <= set(own)
    assert line_dedup.dedup_lines(d).select(*names).distinct().count() == 1
    labels = spark.createDataFrame([(1, 1)], "doc_id long, quality int")
    assert set(same(quality_rules.filter_documents(d, labels))) <= set(own)


def test_sharding(docs):
    got = sharding.shard(docs, 5).collect()
    place, slots = {}, {}
    for r in got:
        assert place.setdefault(r.text, r.shard) == r.shard
        slots.setdefault(r.shard, []).append(r.slot)
    assert all(sorted(s) == list(range(len(s))) for s in slots.values()) and len(got) == docs.count()
    assert sharding.shard(docs.limit(0)).count() == 0


def test_minimax(spark):
    rng = np.random.default_rng(4)
    sizes = rng.integers(1, 50, 300).tolist()
    keys = sorted(rng.integers(0, 2**62, 300).tolist())
    cuts, cap = sharding.minimax_cuts(spark.createDataFrame(list(zip(keys, sizes)), "k long, bytes long"), 7, 3, 2)

    def fits(c):
        n, s = 1, 0
        for x in sizes:
            n, s = (n, s + x) if s + x <= c else (n + 1, x)
        return n <= 7

    assert cap == next(c for c in range(max(sizes), sum(sizes)) if fits(c))
    assert max(sum(s for k, s in zip(keys, sizes) if a <= k < b) for a, b in zip([0, *cuts], [*cuts, 2**63])) <= cap


def test_token_files(spark, docs, tmp_path):
    token_files.write(docs, str(tmp_path / "t"))
    rows = token_files.read(spark, str(tmp_path / "t")).orderBy("start").collect()
    enc, start = tokens.encoder(tokens.vocabulary()), 0
    from pyspark.sql import functions as F

    want = docs.orderBy(F.col("doc_id").asc_nulls_first(), F.xxhash64("text")).collect()
    for r, d in zip(rows, want, strict=True):
        ids = np.frombuffer(enc.ids(d.text), "<u4").tolist() + [2]
        assert (r.doc_id, r.start, r.n_tokens, r.ids) == (d.doc_id, start, len(ids), ids)
        start += len(ids)


def test_blocks():
    rng = np.random.default_rng(1)
    for n in (1, 3, 2000, 30_000):
        ids = (rng.zipf(1.3, n) % 50_000).astype(np.int64)
        block = token_files.encode_block(ids, 50_304)
        assert (token_files.decode_block(block) == ids).all()
    with pytest.raises(ValueError):
        token_files.decode_block(block[:-200] + bytes(200))


def test_token_files_ids(spark, tmp_path):
    """The smallest long is an id like others, a hot id is dealt over tasks, an empty table gives no rows."""
    d = spark.createDataFrame([(-(2**63), "least", 1), (None, "none", 2), *[(5, f"hot {i % 9}", i) for i in range(60)], (2**63 - 1, None, 3)], "doc_id long, text string, h int")
    token_files.write(d, str(tmp_path / "t"), block_ids=40)
    got = token_files.read(spark, str(tmp_path / "t"), with_ids=False).orderBy("start").collect()
    assert [r.doc_id for r in got] == [None, -(2**63), *[5] * 60, 2**63 - 1] and got[-1].n_tokens == 1
    assert all(a.start + a.n_tokens == b.start for a, b in zip(got, got[1:]))
    token_files.write(d.limit(0), str(tmp_path / "e"))
    assert token_files.read(spark, str(tmp_path / "e")).count() == 0


def test_mixed_orders():
    """The blended distribution is one: intervals of all ids tile the total, and id_at() inverts place()."""
    m = token_files.Mixer(60)
    rng = np.random.default_rng(0)
    grid = rng.integers(0, 60, (200, 40))
    for t in range(1, 200):
        m.renew(grid)
        m.predict(grid[t - 1], grid[t - 2])
        m.place(grid[t])
        m.learn(grid[t])
    m.predict(np.full(60, 7), np.full(60, 9))
    m.g1, m.g2 = np.arange(60) % 7, np.arange(60) % 5
    start, freq = m.place(np.arange(60))
    for lane in range(60):
        m1 = [np.full(60, getattr(m, x)[lane]) for x in ("g1", "g2", "a0", "a1", "a2")]
        n = token_files.Mixer(60)
        n.__dict__ |= m.__dict__
        n.g1, n.g2, n.a0, n.a1, n.a2 = m1
        start, freq = (x.astype(np.int64) for x in n.place(np.arange(60)))
        assert start[0] == 0 and (start[1:] == (start + freq)[:-1]).all() and start[-1] + freq[-1] == 1 << token_files.TOTAL_BITS
        assert (n.id_at(start) == np.arange(60)).all() and (n.id_at(start + freq - 1) == np.arange(60)).all()


def test_tokens():
    enc = tokens.encoder(tokens.vocabulary())
    tiny = tokens.Encoder(tokens.vocabulary(), max_parts=5)
    text = "some words come again and again\nand some words are new words here " * 4
    assert tiny.ids(text) == tiny.ids(text) == enc.ids(text) and len(tiny.known) < 30
    odd = ["word. word, word.", "word.\nword.\n\nword.", "a\u00bd. x", "no . dots", "w" * 70 + " end.", "\n\nx y", " lead", "trail ", "", None, "two  spaces", "tab\there."] * 2
    assert [np.frombuffer(x, "<u4").tolist() for x in tokens.Encoder(tokens.vocabulary(), 3).many(odd, 20)] == [enc.tokenizer.encode(t or "", add_special_tokens=False).ids for t in odd]
    for t in ["", " ", " a", "a ", "a  b", "x\n y", "x \ny", "it's\tfine <|endoftext|> é日本", "　 b", "a  b"]:
        assert np.frombuffer(enc.ids(t), "<u4").tolist() == enc.tokenizer.encode(t, add_special_tokens=False).ids


def test_tokens_by_arrays():
    """Ids are those of the library for words of all kinds, whatever the cache holds."""
    rng = np.random.default_rng(6)
    ends = ["", "", "", ".", ",", "...", ".,;:!?", "'s", "5", "\u00bd.", "-x", "\n", "e\u0301."]
    made = lambda: "".join(rng.choice(list("aebnstÄßéж語 "), rng.integers(1, 9))).strip() + str(rng.choice(ends))
    words = [made() for _ in range(3000)]
    texts = [*["".join(f"{w}{' ' if rng.integers(0, 9) else chr(10)}" for w in rng.choice(words, rng.integers(1, 60)))[:-1] for _ in range(300)], None, "", "\n", "\x00 a\x00b \u0120 c", "a \u0120b\nc \u010a"]
    enc = tokens.Encoder(tokens.vocabulary(), 2000)
    want = [enc.tokenizer.encode(t or "", add_special_tokens=False).ids for t in texts]
    for size in (500, 10_000, 10**9):
        assert [np.frombuffer(x, "<u4").tolist() for x in enc.many(texts, size)] == want
        enc.forget()
        assert len(enc.known) == len(enc.older) == 0
    batches = [pa.RecordBatch.from_pydict({"doc_id": list(range(i, i + 5)), "text": pa.array(texts[i : i + 5], pa.string())}) for i in range(0, 305, 5)]
    assert [(d, np.frombuffer(x, "<u4").tolist()) for d, x in enc.rows(iter(batches))] == list(enumerate(want))


def test_cache_is_small():
    """A cached part takes few bytes, in Python and in Arrow together."""
    import tracemalloc

    rng = np.random.default_rng(5)
    words = ["".join(w) for w in rng.choice(list("abcdefghij"), (40_000, 9))]
    enc = tokens.Encoder(tokens.vocabulary())
    enc.ids("warm up, once")
    tracemalloc.start()
    before = tracemalloc.get_traced_memory()[0] + pa.total_allocated_bytes()
    enc.ids(" ".join(words[:20_000])), enc.ids(" ".join(words[20_000:]))
    after = tracemalloc.get_traced_memory()[0] + pa.total_allocated_bytes()
    tracemalloc.stop()
    assert len(enc.known) > 39_000 and (after - before) / len(enc.known) < 80


def test_words_spelt():
    """The library gets a word of letters as one character a byte, and no other characters than the vocabulary's."""
    enc, seen = tokens.Encoder(tokens.vocabulary()), []

    class Plain:
        def encode_batch_fast(self, texts, **k):
            seen.extend(texts)
            return plain.encode_batch_fast(texts, **k)

    plain, enc.plain = enc.plain, Plain()
    text = "first words\nand then \u00e9t\u00e9, words."
    assert np.frombuffer(enc.ids(text), "<u4").tolist() == enc.tokenizer.encode(text, add_special_tokens=False).ids
    assert sorted(" ".join(seen).split(" ")) == sorted(["\u0120first", "\u0120words", "\u010a", "and", "\u0120then", "\u0120\u00c3\u00a9t\u00c3\u00a9"])


def test_quality_classifier(spark):
    good = [(i, f"The river number {i} runs past the old mill and the people of the town like to walk there in the evening {i * 7}.") for i in range(80)]
    bad = [(100 + i, f"BUY!!! ${i} | CLICK!!! ${i * 3} | WIN!!! FREE!!! ${i} | CASH!!! NOW!!!") for i in range(80)]
    d = spark.createDataFrame([*good, *bad, (999, None), (1000, "")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i < 100), 0) for i, _ in good + bad], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in quality_classifier.classify(d, quality_classifier.train(d, labels, 40, 40)).collect()}
    assert np.mean([got[i].predicted == int(i < 100) for i, _ in good + bad]) > 0.95
    assert all(0 <= r.score <= 1 for r in got.values())
    assert quality_classifier.classify(d, quality_classifier.train(d, labels.limit(0))).count() == 162
    # Texts of any length are learned from, by pieces from all over them.
    from pyspark.sql import functions as F

    from ivsearch.llm.common import excerpt

    long = d.withColumn("text", F.repeat("text", 300))
    assert long.select(F.max(F.length("text")), F.max(F.length(excerpt("text", 20_000)))).first()[1] <= 20_100
    m = quality_classifier.train(long, labels, 40, 40)
    assert m.score(good[0][1]) > m.score(bad[0][1])


def test_language(spark):
    a, b = "the cat sat on the mat and the dog ran", "der hund und die katze sind nicht hier gewesen"
    d = spark.createDataFrame([(i, f"{a if i % 2 else b} {i}", "en" if i % 2 else "de") for i in range(60)] + [(99, None, "en"), (98, "12 !", None)], "doc_id long, text string, lang string")
    m = language_id.train(d.where("doc_id < 40"))
    got = {r.doc_id: r.lang_pred for r in language_id.identify(d, m).collect()}
    assert all(got[i] == ("en" if i % 2 else "de") for i in range(60)) and got[99] == got[98] == "und"
    assert (np.abs(m.weights) == 0).mean() > 0.5
    # Numerals are no letters; languages with long texts only, and more than a hundred of them, are learned.
    assert m.predict("\u00bd \u00b2 12") == ("und", 0.0) and m.predict("\u0416")[0] in ("en", "de")
    many = spark.createDataFrame([(i, f"{chr(0x4E00 + i % 130)}{chr(0x5E00 + i % 130)} " * 1500, f"l{i % 130:03}") for i in range(520)], "doc_id long, text string, lang string")
    m = language_id.train(many)
    assert len(m.langs) == 130 and all(m.predict(f"{chr(0x4E00 + i)}{chr(0x5E00 + i)} " * 3)[0] == f"l{i:03}" for i in range(0, 130, 13))


def test_ann(spark):
    r = np.random.default_rng(0)
    v = r.normal(size=(600, 16))
    rows = [(i, x.tolist()) for i, x in enumerate(v)] + [(700, None), (701, [0.0] * 16), (702, [None] + [1.0] * 15), (703, [float("nan")] * 16)]
    d = spark.createDataFrame(rows, "id long, v array<double>")
    got = graph_ann.search(d, d.where("id % 50 = 0"), 10, 250, 12, 24, 1.2, 48).collect()
    hits = 0
    for q in range(0, 600, 50):
        e = np.sqrt(((v - v[q]) ** 2).sum(1))
        e[q] = np.inf
        hits += len(set(np.argsort(e)[:10]) & {x.vec_id for x in got if x.query_id == q})
    assert hits / len(got) >= 0.9 and len(got) == 120
    assert graph_ann.search(d.where("id < 5"), d.where("id < 1")).count() == 4


def test_ann_odd_rows(spark):
    """Mixed lengths, repeated ids, columns of other names, no rows; queries in several blocks give the same as in one."""
    r = np.random.default_rng(1)
    v = r.normal(size=(300, 8))
    rows = [(i, x.tolist(), i) for i, x in enumerate(v)] + [(400, [1.0, 2.0], 0), (401, [float("inf")] * 8, 0), (7, (v[7] + 5).tolist(), 0)]
    d = spark.createDataFrame(rows, "id long, v array<double>, shard int")
    asked = d.where("id % 50 = 0")
    one = graph_ann.index(d, 10, 150, 12, 24)
    a, b = (sorted(tuple(x) for x in graph_ann.nearest(one, asked, 10, 60, block=n).collect()) for n in (1000, 2))
    assert a == b and len(a) == 60 and {x[0] for x in a} == {0, 50, 100, 150, 200, 250}
    assert graph_ann.search(d.limit(0), asked).count() == 0 and graph_ann.search(d, d.limit(0)).count() == 0


def test_ann_copies(spark):
    r = np.random.default_rng(3)
    v = r.normal(size=(700, 16))
    v[1:700:2] = v[1]
    v[0], v[2] = v[1] + 0.01, v[1] - 0.01
    d = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "id long, v array<double>")
    asked = [0, 1, 2, 3, 21, 350, 400, 698, 699]
    got = graph_ann.search(d, d.where(d.id.isin(asked)), 10, 350, 12, 24, 1.2, 48).collect()
    for q in asked:
        e = np.sqrt(((v - v[q]) ** 2).sum(1))
        e[q] = np.inf
        want = np.argsort(e, kind="stable")[:10].tolist()
        found = [x.vec_id for x in sorted((x for x in got if x.query_id == q), key=lambda x: x.rank)]
        assert found == want if q < 100 or q % 2 else len(set(found) & set(want)) >= 9


def test_quality_rules(spark, docs):
    for r in quality_rules.measures(docs).collect():
        w = WORD.findall(r.text or "")
        seen = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
        covered = {j for i, x in enumerate(seen) if seen.count(x) > 1 for j in (i, i + 1, i + 2)} if len(w) < 500 else set(range(len(w)))
        lines = [x for x in (r.text or "").split("\n") if WORD.search(x)]
        assert (r.n_words, r.word_chars, r.n_repeat_words, r.n_dup_lines) == (len(w), sum(map(len, w)), len(covered), len(lines) - len(set(lines)))
    from math import comb

    from pyspark.sql import functions as F

    for n in (10, 700, 900, 3000):
        level, a = 0.01, 0.01
        tail, want = 0.0, None
        for k in range(n + 1):
            tail += comb(n, k) * a**k * (1 - a) ** (n - k)
            if tail > level:
                break
            want = k
        assert spark.range(1).select(quality_rules.allowed(F.lit(n).cast("long"), a, F.lit(level))).first()[0] == want
    labels = spark.createDataFrame([(1, 1), (1, 0), (None, 1)], "doc_id long, quality int")
    assert quality_rules.judge(docs, labels).count() == docs.count()


def test_quality_rules_pool(spark):
    text = " ".join(f"word{i}" for i in range(60))
    good = [(i, f"{text} {i}", ("a", "b", None)[i % 3]) for i in range(1500)]
    bad = [(5000 + i, f"{text} {'#' * 200} {i}", ("a", "b", None, "c")[i % 4]) for i in range(8)]
    d = spark.createDataFrame(good + bad, "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, 1) for i, *_ in good], "doc_id long, quality int")
    assert {r.doc_id for r in quality_rules.judge(d, labels).where("not kept and not base_failed").collect()} == {i for i, *_ in bad}
