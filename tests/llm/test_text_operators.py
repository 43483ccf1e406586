"""Quality rules, substring and suffix-array removal, Jaccard join, pipeline, against brute force."""

import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from rulecredit.llm import anchors, jaccard_join, quality, substring, suffix_dedup
from rulecredit.llm import bytehash as bh
from rulecredit.llm.runtime import SharedStore
from tests.llm import brute

VOCAB = [f"{a}{b}" for a in ("ba", "Ko", "ré", "zu", "xi", "lo") for b in ("", "n", "tß", "mm", "q9")]


def corpus(seed=1):
    """Clean, copied, near-copied, tiny, blank and null texts, with shared passages and odd spaces."""
    rng = random.Random(seed)
    make = lambda n: " ".join(rng.choice(VOCAB) for _ in range(n))
    passage = make(90)
    docs = {}
    for i in range(40):
        docs[i] = make(rng.randint(30, 160))
    for i in range(40, 52):  # near copies of document 3
        w = docs[3].split()
        for _ in range(rng.randint(0, 4)):
            w[rng.randrange(len(w))] = rng.choice(VOCAB)
        docs[i] = " ".join(w)
    for i in range(52, 58):
        docs[i] = docs[5]
    for i in range(58, 66):
        docs[i] = make(20) + "\n" + passage + "\t" + make(15)
    docs |= {66: "", 67: None, 68: " \n\t ", 69: "one", 70: "ONE", 71: "a b c d", 72: "A B c d", 73: "la " * 600}
    docs |= {74: docs[73] + "end", 75: "x y\x1cz " * 30, 76: "€" * 500, 77: "é€" + "€" * 500, 78: passage.replace(" ", " \x0b")}
    for n, i in enumerate(range(80, 92)):  # small sets around every size filter
        docs[i] = " ".join(VOCAB[: 6 + n % 8])
    return docs


@pytest.fixture(scope="module")
def docs():
    return corpus()


@pytest.fixture(scope="module")
def frame(spark, docs):
    return spark.createDataFrame(list(docs.items()), "doc_id long, text string").repartition(5).cache()


def rows_of(docs):
    """The documents and rows that repeat an id (with the same text, another, none), or have none."""
    more = [(5, "other " * 3 + docs[60]), (None, docs[58]), (None, "z" * 900), (3, None), (3, docs[3]), (58, docs[58])]
    return list(docs.items()) + more


@pytest.fixture(scope="module")
def messy(spark, docs, tmp_path_factory):
    """(folder, rows) with null and repeated ids and clashing column names."""
    rows = rows_of(docs)
    folder = str(tmp_path_factory.mktemp("messy"))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    df.selectExpr("doc_id", "'x' as h", "text", "1 as starts", "2 as _row", "'s' as sid").write.parquet(f"{folder}/documents.parquet")
    return folder, rows


def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string")


def test_quality_counts(frame, docs):
    for r in quality.apply_quality_rules(frame).collect():
        got = (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed)
        assert got == brute.quality(docs[r.doc_id]), r.doc_id


def test_quality_verdicts(spark):
    clean = "The cat sat on the mat and it was happy with the warm sun that day in the old house by the sea " \
            "where she had been for many years before they came to see her again"
    rows = [(1, clean, "en"), (2, clean.replace(" ", "$$$ "), "en"), (3, "word " * 50, "en"), (4, None, "en"), (5, clean.upper().replace(" ", "!! "), "en")]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_words string")
    kept = quality.kept_documents(df)
    assert kept.columns == df.columns and [r.doc_id for r in kept.collect()] == [1]
    assert quality.kept_documents(empty(spark)).count() == 0


@pytest.mark.parametrize("shard", [60_000, 100, 20])
def test_substring(spark, messy, monkeypatch, shard):
    monkeypatch.setattr(substring, "SHARD_WORDS", shard)
    folder, rows = messy
    got = [tuple(r) for r in substring.op4_suffix_automata_dedup(spark, folder).collect()]
    assert Counter(got) == Counter(brute.substring(rows))
    assert substring.removal_spans(empty(spark), SharedStore(spark, "t")).count() == 0


def test_suffix_automaton():
    rng = random.Random(5)
    for _ in range(200):
        texts = [[rng.randrange(3) for _ in range(rng.randint(1, 14))] for _ in range(6)]
        k = rng.randint(1, 4)
        machine = substring.SuffixAutomaton()
        for i, t in enumerate(texts):
            machine.add(t, i)
        for t in texts:
            want = [next(i for i, u in enumerate(texts) if any(u[j : j + k] == t[a : a + k] for j in range(len(u) - k + 1))) for a in range(len(t) - k + 1)]
            assert machine.owners(t, k) == want


def test_suffix_intervals():
    rng = random.Random(6)
    for _ in range(60):
        blocks = [bytes(rng.choice(b"ab") for _ in range(rng.randint(6, 30))) for _ in range(rng.randint(1, 6))]
        weights = [rng.randint(1, 2) for _ in blocks]
        count = {}
        for b, w in zip(blocks, weights):
            for i in range(len(b) - 5):
                count[b[i : i + 6]] = count.get(b[i : i + 6], 0) + w
        flags = suffix_dedup.repeated_windows(blocks, weights, 6)
        assert [f.tolist() for f in flags] == [[count[b[i : i + 6]] > 1 for i in range(len(b) - 5)] for b in blocks]


@pytest.mark.parametrize(("length", "shard", "spreads"), [(40, 10**6, (16, 1)), (40, 500, (5, 2, 1)), (400, 10**6, (16, 1)), (400, 500, (16, 1)), (400, 500, (1,))])
def test_suffix_removal(spark, messy, monkeypatch, length, shard, spreads):
    monkeypatch.setattr(suffix_dedup, "SHARD_BYTES", shard)
    monkeypatch.setattr(suffix_dedup, "SPREADS", spreads)
    folder, rows = messy
    df = spark.read.parquet(f"{folder}/documents.parquet")
    out = suffix_dedup.remove_repeats(df, length)
    assert out.schema == df.schema
    want = [(k, None if t is None else x.decode("utf-8", errors="ignore")) for (k, t), (x, _) in zip(rows, brute.cut_bytes(rows, length))]
    assert Counter((r.doc_id, r.text) for r in out.collect()) == Counter(want)
    assert suffix_dedup.remove_repeats(empty(spark), length).count() == 0


def test_passages_by_words(spark, docs):
    rows = list(docs.items())
    out = suffix_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), 60, 20, 150)
    want = {k: x.decode("utf-8", errors="ignore") for (k, _), (x, _) in zip(rows, brute.cut_bytes(rows, 60, 20, 150))}
    assert {r.doc_id: r.text or "" for r in out.collect()} == want


def test_suffix_digest(spark, messy):
    folder, rows = messy
    got = [tuple(r) for r in suffix_dedup.op9_suffix_interval_dedup(spark, folder).collect()]
    sizes = [len((t or "").encode()) for _, t in rows]
    want = [(k, n, n - len(x), spans, brute.digest(x)) for (k, _), n, (x, spans) in zip(rows, sizes, brute.cut_bytes(rows))]
    assert Counter(got) == Counter(want)


def test_passages_of_over_50_words(spark, tmp_path):
    """Planted in three texts each: op9 removes those of 400 bytes and more, by its contract, a stage by words the shorter ones too."""
    rng = random.Random(12)
    make = lambda n: " ".join(rng.choice(VOCAB) for _ in range(n))

    def sized(n_bytes):
        head = make(52)
        return head + " " + "x" * (n_bytes - len(head.encode()) - 1)

    sizes = (271, 394, 399, 400, 450)
    rows = [(i, make(80)) for i in range(20)]
    for n, size in enumerate(sizes):
        p = sized(size)
        assert len(p.encode()) == size and len(p.split()) > 50
        rows += [(100 + 10 * n + i, f"{make(40)} {'abc'[i]}{p}{'def'[i]} {make(40)}") for i in range(3)]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r.n_removed for r in suffix_dedup.op9_suffix_interval_dedup(spark, str(tmp_path)).collect()}
    planted = {100 + 10 * n + i: size for n, size in enumerate(sizes) for i in range(3)}
    assert got == {k: planted.get(k, 0) if planted.get(k, 0) >= 400 else 0 for k, _ in rows}
    out = suffix_dedup.remove_repeats(spark.read.parquet(f"{tmp_path}/documents.parquet"), 200, 51)
    left = {r.doc_id: len(r.text.encode()) for r in out.collect()}
    assert left == {k: len(t.encode()) - planted.get(k, 0) for k, t in rows}


@pytest.mark.parametrize("words", [1, 1 << 18])
def test_only_rows_with_a_partner_move(spark, monkeypatch, words):
    """A filter before the joins on texts loses no row that meets one, and keeps few others when it has room."""
    monkeypatch.setattr(anchors, "MOST_WORDS", words)
    rows = spark.range(3000).select(F.xxhash64("id").alias("h"), "id")
    got = {r["id"]: r["near"] for r in anchors.possible(rows, rows.where("id % 10 = 3")).collect()}
    near = {i for i, n in got.items() if n}
    assert len(got) == 3000 and near >= set(range(3, 3000, 10))
    assert len(near) < 600 or words == 1
    assert not any(r["near"] for r in anchors.possible(rows, rows.where("false")).collect())


def test_common_line_in_many_surroundings(spark, monkeypatch):
    """One line in every text, surroundings all different, some texts sharing a little around it."""
    monkeypatch.setattr(suffix_dedup, "SHARD_BYTES", 2_000)
    monkeypatch.setattr(substring, "SHARD_WORDS", 200)
    rng = random.Random(11)
    make = lambda n: " ".join(rng.choice(VOCAB) for _ in range(n))
    line, near = make(40), [make(6) for _ in range(3)]
    rows = [(i, f"{make(20)} {rng.choice(near)} {line} {rng.choice(near)} {make(20)}") for i in range(120)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    out = {r.doc_id: r.text for r in suffix_dedup.remove_repeats(df, 120).collect()}
    assert out == {k: x.decode("utf-8", errors="ignore") for (k, _), (x, _) in zip(rows, brute.cut_bytes(rows, 120))}
    spans = substring.removal_spans(df, SharedStore(spark, "t"))
    got = {r.doc_id: substring._kept_words(r.text, r.starts, r.counts, 13) for r in df.join(spans, "doc_id", "left").collect()}
    assert {(k, n, n - len(w), brute.digest(b" ".join(w))) for k, (n, w) in got.items()} == set(brute.substring(rows))


def thue_morse(a, b, bits):
    return [(a, b)[i.bit_count() & 1] for i in range(1 << bits)], [(b, a)[i.bit_count() & 1] for i in range(1 << bits)]


def test_structured_texts(spark):
    """Strings whose polynomial hashes agree modulo a power of two are still told apart."""
    one, two = ("".join(w) for w in thue_morse("a", "b", 11))
    left, right = (" ".join(w) for w in thue_morse("w", "v", 11))
    rows = [(1, "x y z " + one), (2, "x y z " + two), (3, left), (4, right), (5, one + " u v"), (6, two + " u v")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = jaccard_join.jaccard_components(df, SharedStore(spark, "t"))
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got.collect()} == brute.jaccard(dict(rows))
    out = {r.doc_id: r.text for r in suffix_dedup.remove_repeats(df).collect()}
    assert out == {k: x.decode() for (k, _), (x, _) in zip(rows, brute.cut_bytes(rows))}
    spans = substring.removal_spans(df, SharedStore(spark, "t"))
    kept = {r.doc_id: substring._kept_words(r.text, r.starts, r.counts, 13) for r in df.join(spans, "doc_id", "left").collect()}
    assert {(k, n, n - len(w), brute.digest(b" ".join(w))) for k, (n, w) in kept.items()} == set(brute.substring(rows))


def components_of(rows):
    """[(doc_id, n_shingles, component_id)] by brute force, every row a text of its own."""
    own = brute.jaccard({i: t for i, (_, t) in enumerate(rows)})
    low = {}
    for i, (_, c) in own.items():
        ids = [x for x in (rows[i][0], low.get(c)) if x is not None]
        low[c] = min(ids) if ids else None
    return [(rows[i][0], n, low[c]) for i, (n, c) in own.items()]


def test_jaccard(spark, messy):
    folder, rows = messy
    got = [tuple(r) for r in jaccard_join.op10_size_aware_jaccard(spark, folder).collect()]
    assert Counter(got) == Counter(components_of(rows))
    assert jaccard_join.jaccard_components(empty(spark), SharedStore(spark, "t")).count() == 0


def test_jaccard_with_frequent_shingles(spark, docs, monkeypatch):
    """Lists of frequent shingles dealt by set, hot joins spread, a forgetful task."""
    from rulecredit.llm import runtime

    monkeypatch.setattr(jaccard_join, "FREQUENT_SHARE", 0.0)
    monkeypatch.setattr(runtime, "KEY_ROWS", 3)
    rows = list(docs.items())
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = jaccard_join.jaccard_components(df, SharedStore(spark, "t"))
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got.collect()} == brute.jaccard(docs)


def test_jaccard_stage(spark, messy):
    folder, rows = messy
    df = spark.read.parquet(f"{folder}/documents.parquet")
    kept = jaccard_join.one_per_component(df)
    assert kept.columns == df.columns
    own = brute.jaccard({i: t for i, (_, t) in enumerate(rows)})
    left = {}
    for i, (n, c) in own.items():  # of each component the smallest id's text, none after all others; blank texts all stay
        group = c if n else (rows[i][0], rows[i][1])
        key = (rows[i][0] is None, rows[i][0] or 0)
        if group not in left or key < left[group][0]:
            left[group] = (key, rows[i])
    got = [(r.doc_id, r.text) for r in kept.collect()]
    assert len(got) == len(left) and {k for k, _ in got} == {r[0] for _, r in left.values()}
    texts = {k: {t for j, t in rows if j == k} for k, _ in got}
    assert all(t in texts[k] for k, t in got)


def test_block_passes_on_fewer_links_than_sets():
    """A list of many sets that all link gives one link a set, not one a pair; sets below the threshold give none."""
    base = [f"w{i}" for i in range(60)]
    texts = [" ".join([*base[:k], f"x{k}", *base[k + 1 :]]) for k in range(0, 60, 2)]
    texts = [*texts, *(" ".join(f"{n}y{i}" for i in range(60)) for n in range(3))]
    sets = [t for _, t in jaccard_join.shingle_sets(pa.array(texts))]
    rows = [(1, 0, 0, i, len(t), -1, i, jaccard_join.parity_bits(t), 0, x) for i, (t, x) in enumerate(zip(sets, texts))]
    kinds = [pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.int32(), pa.string()]
    batch = pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(zip(*rows), kinds)], list("abcdefghij"))
    named = sum(b.num_rows for b in jaccard_join._paired_sets(iter([batch.select(range(9))])))
    links = [p for b in jaccard_join._linked_sets(iter([batch])) for p in zip(*(c.to_pylist() for c in b.columns))]
    assert 30 <= named <= 33 and len(links) == 29 and {k for p in links for k in p} == set(range(30))


def test_needed_overlap():
    for s in range(1, 40):
        for t in range(1, 40):
            linked = [o for o in range(min(s, t) + 1) if 100 * o >= 75 * (s + t - o)]
            assert min(linked, default=10**6) >= jaccard_join.need(s, t)
    assert jaccard_join.choose_boundary({}) == 1
    assert jaccard_join.choose_boundary({3: 100, 4: 100}) > 4


def test_parity_bound():
    rng = np.random.default_rng(1)
    for _ in range(50):
        a = np.unique(rng.integers(0, 2**63, rng.integers(1, 300)).astype(np.uint64))
        b = np.unique(np.concatenate([a[: len(a) // 2 + 1], rng.integers(0, 2**63, rng.integers(0, 200)).astype(np.uint64)]))
        p, q = (np.frombuffer(jaccard_join.parity_bits(x), np.uint8) for x in (a, b))
        size = min(len(p), len(q))
        differ = int(np.bitwise_count(jaccard_join._folded(p, size) ^ jaccard_join._folded(q, size)).sum())
        assert len(np.intersect1d(a, b)) <= (len(a) + len(b) - differ) // 2


def test_anchors_follow_content():
    rng = np.random.default_rng(2)
    text = rng.integers(97, 100, 900).astype(np.uint8)
    one, two = np.concatenate([text[:300], text[100:220]]), np.concatenate([text[50:300], text[90:230]])
    seen = []
    for data in (one, two):
        prefix = bh.Buffer(data, np.array([0, len(data)]), 0).prefix()
        at = np.arange(len(data) - 7)
        b = anchors.find_blocks(bh.range_hash(prefix, at, at + 8), data, np.array([0, len(data)]), 30, 8)
        assert b.count.sum() == len(data) - 29
        found = {}
        for s, c, a in zip(b.start.tolist(), b.count.tolist(), b.anchor.tolist()):
            found |= {data[i : i + 30].tobytes(): a for i in range(s, s + c)}
        seen.append(found)
    shared = set(seen[0]) & set(seen[1])
    assert shared and all(seen[0][w] == seen[1][w] for w in shared)


def test_words_match_bytes_split():
    import pyarrow as pa

    texts = list(corpus().values())
    for buf in bh.slices(pa.array(texts, pa.string()), 500):
        w = bh.words(buf)
        for i in range(len(buf.offs) - 1):
            a, b = w.offs[i], w.offs[i + 1]
            got = [buf.data[x:y].tobytes() for x, y in zip(w.start[a:b], w.end[a:b])]
            assert got == brute.words(texts[buf.first + i])
