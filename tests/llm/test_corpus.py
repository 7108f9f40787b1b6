"""Operators over the whole corpus, against brute force."""

import collections
import hashlib
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from lowbits.llm import engine, line_dedup, mixing, ngram_join, substring_dedup, suffix_dedup, toxicity, url_lists

SF = "/root/testdata/sf0.001"
LOW = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
BASE = "one two three four five six seven eight nine ten eleven twelve"
EDITED = [
    BASE,
    BASE.upper() + "\n\n" + BASE,
    BASE.replace("six", "sieben"),
    BASE.replace("six ", ""),
    "zero " + BASE + "\nshort line\nshort line",
    BASE.replace("six", "a").replace("nine", "b"),
    None,
    "",
    "\n\n",
    "wörd " * 20 + "\n" + "wörd " * 20,
]


def given(spark):
    return spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars")


def more(spark, texts, start=10**6):
    return spark.createDataFrame([(start + i, t, "en", "s", 0) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")


def one_edit(a, b):
    if len(a) == len(b):
        return sum(x != y for x, y in zip(a, b)) <= 1
    a, b = sorted((a, b), key=len)
    return len(b) - len(a) == 1 and any(b[:i] + b[i + 1 :] == a for i in range(len(b)))


def brute_lines(docs):
    forms = collections.defaultdict(list)
    for i, t in sorted(docs):
        for k, line in enumerate((t or "").split("\n")):
            if w := tuple(WORD.findall(line.translate(LOW))):
                forms[w].append((i, k))
    first = {w: min(o) for w, o in forms.items()}
    by = collections.defaultdict(set)
    for w in forms:
        if len(w) >= 8:
            for v in [w, *(w[:i] + w[i + 1 :] for i in range(len(w)))]:
                by[v].add(w)
    gone = {y for ws in by.values() for x in ws for y in ws if first[x] < first[y] and one_edit(x, y)}
    out = collections.defaultdict(set)
    for w, o in forms.items():
        for p in o:
            if w in gone or p > first[w]:
                out[p[0]].add(p[1])
    return {i: sorted(out[i]) for i, _ in docs}


def test_line_dedup(spark):
    docs = given(spark).unionByName(more(spark, EDITED))
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    want = brute_lines(rows)
    assert {r.doc_id: r.removed for r in line_dedup.line_report(docs).collect()} == want
    assert want[10**6 + 2] == [0] and want[10**6 + 5] == [] and want[10**6 + 4] == [0, 2]
    texts = dict(rows)
    for r in line_dedup.drop_lines(docs).collect():
        keep = [x for k, x in enumerate(texts[r.doc_id].split("\n")) if k not in want[r.doc_id]] if texts[r.doc_id] is not None else None
        assert r.text == ("\n".join(keep) if keep is not None else None)
    assert line_dedup.line_report(more(spark, [])).count() == 0


def test_line_dedup_with_shared_and_null_ids_and_clashing_columns(spark):
    other = "a line of its own that nobody else has"
    rows = [(1, BASE), (5, other + "\n" + BASE), (5, BASE + "\n" + other.replace("own", "mine") + " x y"), (None, BASE), (6, None), (6, None), (7, "word " * 100_000 + "\n" + BASE)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumns({x: F.lit(1) for x in ("_id", "_removed", "removed", "tag", "d", "t", "line", "lines", "n_chars")})
    out = line_dedup.drop_lines(docs)
    got = sorted(((r.doc_id or 0, r.text) for r in out.collect()), key=str)
    assert out.columns == docs.columns and out.schema["n_chars"].dataType == docs.schema["n_chars"].dataType
    assert got == sorted([(1, BASE), (5, other), (5, other.replace("own", "mine") + " x y"), (0, BASE), (6, None), (6, None), (7, "word " * 100_000)], key=str)
    assert sorted((r.doc_id or 0, tuple(r.removed)) for r in line_dedup.line_report(docs).collect()) == [(0, ()), (1, ()), (5, (0,)), (5, (1,)), (6, ()), (6, ()), (7, (1,))]
    assert line_dedup.drop_lines(docs.where("false")).count() == 0


def test_lines_of_one_template(spark):
    """Thousands of lines that share a variant leave an entry for each position, and the result of brute force."""
    rng = np.random.default_rng(4)
    frame = BASE.split()[:9]
    lines = [" ".join(frame[:k] + [f"w{int(rng.integers(10**6))}"] + frame[k:]) for k in (4, 4, 4, 4, 9, 0) for _ in range(50)]
    for own in (0, 150, 300):  # the variant itself comes first, amid, last
        mixed = [*lines[:own], " ".join(frame), *lines[own:]]
        texts = ["\n".join(mixed[i : i + 7]) for i in range(0, len(mixed), 7)]
        docs = more(spark, texts).repartition(5)
        want = brute_lines([(r.doc_id, r.text) for r in docs.collect()])
        assert {r.doc_id: r.removed for r in line_dedup.line_report(docs).collect()} == want
        assert sum(map(len, want.values())) >= len(lines) - 3
    n = 5000
    e = np.zeros(2 * n, line_dedup._SPOT)
    e["key"], e["doc"], e["role"] = 9, np.arange(2 * n), line_dedup.SHORTER + np.arange(2 * n) % 2
    left, pairs = line_dedup._earlier(e)
    assert left["doc"].tolist() == [0, 1] and not any(len(x) for x, _ in pairs)


def brute_classes(docs, w=5):
    sets = {}
    for i, t in docs:
        x = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOW))
        sets[i] = {tuple(x[k : k + w]) for k in range(len(x) - w + 1)} if len(x) >= w else ({tuple(x)} if x else set())
    ids, root = sorted(sets), {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for p, a in enumerate(ids):
        for b in ids[:p]:
            x, y = sets[a], sets[b]
            if x and y and 4 * min(len(x), len(y)) >= 3 * max(len(x), len(y)):
                n = len(x & y)
                if 100 * n >= 75 * (len(x) + len(y) - n):
                    r, s = sorted((find(a), find(b)))
                    root[s] = r
    return {i: (len(sets[i]), find(i)) for i in ids}


def near_copies(seed=5):
    rng = np.random.default_rng(seed)
    out = []
    for n in (3, 6, 12, 40, 130, 300, 600):
        words = [f"w{n}x{i}" for i in range(n)]
        for edits in range(0, max(2, n // 12)):
            x = list(words)
            for k in rng.choice(n, min(edits, n), replace=False):
                x[k] = f"e{edits}y{k}"
            out.append(" ".join(x))
    return out + ["a b", "A  b", "a", "", None, "  "]


def test_jaccard_classes(spark):
    docs = given(spark).unionByName(more(spark, near_copies()))
    want = brute_classes([(r.doc_id, r.text) for r in docs.collect()])
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.classes(docs).collect()}
    assert got == want
    kept = {r.doc_id for r in ngram_join.representatives(docs).collect()}
    assert kept == {i for i, (_, c) in want.items() if i == c}


def test_jaccard_with_shared_and_null_ids(spark):
    """Rows (1, A+p), (1, B+p), (2, A+q), (3, B+q): both texts under one id link, and so does a text without an id."""
    a, b = " ".join(f"a{i}" for i in range(60)), " ".join(f"b{i}" for i in range(60))
    c, p, q = " ".join(f"c{i}" for i in range(60)), " p1 p2", " q1 q2"
    rows = [(1, a + p), (1, b + p), (2, a + q), (3, b + q), (None, c + p), (7, c + q), (8, c + " r1 r2"), (8, c + " r1 r2"), (9, None), (None, None), (10, "long " * 50_000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumns({x: F.lit(1) for x in ("th", "d", "t", "fp", "n", "kind", "component", "_drop")})
    got = collections.Counter((r.doc_id, r.component_id) for r in ngram_join.classes(docs).collect())
    assert got == {(1, 1): 2, (2, 1): 1, (3, 1): 1, (None, None): 2, (7, 7): 1, (8, 7): 2, (9, 9): 1, (10, 10): 1}
    kept = ngram_join.representatives(docs)
    assert kept.columns == docs.columns and sorted((r.doc_id or 0) for r in kept.collect()) == [0, 0, 1, 1, 7, 9, 10]
    assert ngram_join.classes(docs.where("false")).count() == 0 and ngram_join.representatives(docs.where("false")).count() == 0


def test_large_group_is_split_and_frequent_tokens_use_deletions(spark, monkeypatch):
    """A group of near copies over several blocks, whose tokens are all frequent."""
    monkeypatch.setattr(ngram_join, "BLOCK", 50)
    monkeypatch.setattr(ngram_join, "LOCALLY_FREQUENT", 20)
    rng = np.random.default_rng(3)
    texts = []
    for _ in range(140):
        x = [f"t{i}" for i in range(220)]
        for k in rng.choice(220, int(rng.integers(0, 9)), replace=False):
            x[k] = f"r{rng.integers(1 << 40)}"
        texts.append(" ".join(x))
    docs = more(spark, texts + texts[:30], 0).repartition(5)
    want = brute_classes([(r.doc_id, r.text) for r in docs.collect()])
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.classes(docs).collect()} == want


def test_strays_meet_the_core_and_each_other(spark, monkeypatch):
    """Chains whose ends are far apart, over several blocks: links that no leader sees are found among strays."""
    monkeypatch.setattr(ngram_join, "BLOCK", 4)
    texts = []
    for c in range(6):
        x = [f"c{c}w{i}" for i in range(64)]
        for step in range(12):  # each differs from the one before in a few words, ends share little
            texts.append(" ".join(x))
            x[5 * step % 60] = f"c{c}s{step}"
            x[5 * step % 60 + 1] = f"c{c}t{step}"
    docs = more(spark, texts, 0).repartition(6)
    want = brute_classes([(r.doc_id, r.text) for r in docs.collect()])
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.classes(docs).collect()} == want
    assert len({c for _, c in want.values()}) < len(texts)


def test_segments_meet_for_every_pair_within_reach():
    """Pigeonhole: two sets within the bound always share a key, for rare and frequent tokens."""
    rng = np.random.default_rng(1)
    for n in (1, 2, 5, 20, 97, 128, 129, 400, 513, 900):
        for kinds in ([0], [2, 3], [9, 15], list(range(ngram_join.CLASSES))):
            token = lambda m: rng.integers(1, 1 << 59, m).astype(np.uint64) << np.uint64(4) | rng.choice(kinds, m).astype(np.uint64)  # noqa: E731, B023
            base = token(n)
            for _ in range(4):
                lost = int(n // 7)
                other = base.copy()
                other[rng.choice(n, lost, replace=False)] = token(lost)
                a, b = (ngram_join.segment_keys(n, 0, np.unique(x)) for x in (base, other))
                assert len(np.intersect1d(a, b))


def test_allocation_follows_cost():
    place = ngram_join.allocation()
    for c in range(ngram_join.CLASSES):
        assert (place[c] < ngram_join.CLASSES) == (ngram_join.exact_cost(c) <= ngram_join.deletion_cost())
    assert place[0] == 0 and place[-1] == ngram_join.CLASSES and (np.diff(place) >= 0).all()


def brute_strings(docs, length):
    raw = {i: (t or "").encode() for i, t in docs}
    count = collections.Counter(b[k : k + length] for b in raw.values() for k in range(len(b) - length + 1))
    out = {}
    for i, b in raw.items():
        m = bytearray(len(b))
        for k in range(len(b) - length + 1):
            if count[b[k : k + length]] > 1:
                m[k : k + length] = b"\1" * length
        kept = bytes(x for x, y in zip(b, m) if not y)
        out[i] = (len(b), sum(m), len(re.findall(b"\1+", bytes(m))), hashlib.sha256(kept).hexdigest())
    return out


@pytest.mark.parametrize("bucket", [4096, 2])
def test_suffix_dedup(spark, bucket, monkeypatch):
    monkeypatch.setattr(suffix_dedup.repeated_spans, "__defaults__", (suffix_dedup.LENGTH, suffix_dedup.GRAM, bucket))
    rng = np.random.default_rng(2)
    word = lambda n: "".join(chr(97 + x) for x in rng.integers(0, 26, n))
    p, q = word(450), word(399)
    texts = [word(50) + p + word(70), p + word(300), word(9) + p[:430], q + "x", q + "y", "é" * 500, "ab" * 450, None, "", p * 3, word(1000) + p[20:440] + word(5)]
    docs = given(spark).unionByName(more(spark, texts))
    want = brute_strings([(r.doc_id, r.text) for r in docs.collect()], 400)
    assert {r.doc_id: tuple(r)[1:5] for r in suffix_dedup.report(docs).collect()} == want


def test_suffix_dedup_on_odd_rows(spark):
    """Null and shared ids, two texts under one id, repeated rows, clashing columns, a very long text, an empty table."""
    p = "".join(chr(97 + x) for x in np.random.default_rng(4).integers(0, 26, 600))
    texts = [(1, p + "x"), (1, "y" + p), (1, "other"), (None, p), (None, None), (2, "ab c" * 3), (2, "ab c" * 3), (3, "word " * 60_000), (4, None)]
    docs = spark.createDataFrame(texts, "doc_id long, text string").withColumns({c: F.lit(1) for c in ("d", "t", "th", "row", "anchor", "spans", "start")})
    want = brute_strings(list(enumerate(t for _, t in texts)), 400)
    got = collections.Counter(tuple(r)[:5] for r in suffix_dedup.report(docs).collect())
    assert got == collections.Counter((texts[k][0], *v) for k, v in want.items())
    assert suffix_dedup.report(docs.where("false")).count() == 0


def test_shared_passages_of_50_to_120_words(spark):
    """Every pair of documents with 51 words in common is found; those without 34 are left alone."""
    rng = np.random.default_rng(9)
    word = lambda: "".join(chr(97 + x) for x in rng.integers(0, 26, int(rng.integers(2, 9))))
    texts, shared = [], []
    for k in range(60):
        passage = [word() for _ in range(int(rng.integers(51, 121)) if k % 3 else int(rng.integers(5, 34)))]
        for _ in range(2 + k % 4):
            texts.append(" ".join([*(word() for _ in range(int(rng.integers(0, 90)))), *passage, *(word() for _ in range(int(rng.integers(0, 90))))]))
            shared.append(bool(k % 3))
    docs = more(spark, [*texts, None, "", "x " * 50], 0).repartition(7)
    rows = {r.doc_id: r.n_shared_passages for r in suffix_dedup.report(docs).collect()}
    assert [rows[i] > 0 for i in range(len(texts))] == shared and len(rows) == len(texts) + 3
    same = {r.n_shared for r in suffix_dedup.shared_passages(more(spark, [texts[3]], 7).unionByName(more(spark, [texts[3]], 7))).collect()}
    assert not same  # a repeated row is no other document


def test_cover_takes_any_two_positions_to_the_sample():
    for v in (8, 32, 64):
        cover = suffix_dedup.difference_cover(v)
        s = suffix_dedup.cover_shifts(v)
        i, j = np.indices((v, v))
        assert np.isin((i + s) % v, cover).all() and np.isin((j + s) % v, cover).all() and len(cover) <= v // 2


def brute_units(rows, unit):
    """(n_units, n_removed, n_repeated, digest of what stays) by (doc_id, text); rows without an id keep everything."""
    cut = {"line": r"[^\n]*\n|[^\n]+$", "paragraph": r"(?s).*?\n\n|.+$", "sentence": r"(?s).*?(?:\n|(?<=[.!?]) )|.+$"}[unit]
    form = lambda u: tuple(WORD.findall(u.translate(LOW)))
    texts = {(i, t or "") for i, t in rows if i is not None}
    places = collections.defaultdict(set)
    for i, t in texts:
        for k, u in enumerate(re.findall(cut, t)):
            if len(form(u)) >= 8:
                places[form(u)].add((i, t, k))
    out = {}
    for i, t in {(i, t or "") for i, t in rows}:
        units = re.findall(cut, t)
        mine = [places.get(form(u), ()) if i is not None else () for u in units]
        gone = [len(p) > 1 and (i, k) != min((x, z) for x, _, z in p) for k, p in enumerate(mine)]
        out[(i, t)] = (len(units), sum(gone), sum(len(p) > 1 for p in mine), hashlib.sha256("".join(u for u, g in zip(units, gone) if not g).encode()).hexdigest())
    return out


@pytest.mark.parametrize("unit", ["line", "paragraph", "sentence"])
def test_unit_dedup(spark, unit):
    docs = given(spark).unionByName(more(spark, [*EDITED, BASE + ". " + BASE + "! " + BASE, BASE + "\n\n" + BASE, BASE + "." + " x" * 200_000]))
    docs = docs.unionByName(docs.where("doc_id = 1000001")).withColumns({c: F.lit(1) for c in ("d", "t", "th", "unit", "units", "gone", "kept", "part")})
    docs = docs.unionByName(docs.where("doc_id % 50 = 0").withColumn("doc_id", F.lit(None).cast("long")))
    want = brute_units([(r.doc_id, r.text) for r in docs.collect()], unit)
    got = substring_dedup.dedup(docs, unit).collect()
    assert len(got) == docs.count()
    texts = collections.defaultdict(set)
    for i, t in want:
        texts[i].add(t)
    for r in got:
        assert any((r.n_units, r.n_removed, r.n_repeated, r.kept_sha256) == want[(r.doc_id, t)] for t in texts[r.doc_id])
        assert hashlib.sha256(bytes(r.kept)).hexdigest() == r.kept_sha256
        if r.doc_id is not None:
            raw, at, parts = next(iter(texts[r.doc_id])).encode(), 0, []
            for s in r.removed:
                parts.append(raw[at : s.start])
                at = s.end
            assert b"".join([*parts, raw[at:]]) == bytes(r.kept)
    assert substring_dedup.dedup(docs.where("false"), unit).count() == 0


def test_unit_dedup_tells_texts_of_one_id_apart(spark):
    docs = spark.createDataFrame([(5, BASE + "\nown line of the first text, with nine words"), (5, "other\n" + BASE), (6, BASE), (None, BASE)], "doc_id long, text string")
    got = collections.Counter((r.doc_id, r.n_removed, r.n_repeated) for r in substring_dedup.dedup(docs, "line", with_kept=False).collect())
    assert got[(6, 1, 1)] == 1 and got[(None, 0, 0)] == 1 and got[(5, 0, 1)] == 1 and got[(5, 1, 1)] == 1


def test_repeated_lines_of_short_sentences_go_whole(spark):
    line, long = "One two three. Four five six. Seven eight nine.", "a b c d e f g h i."
    docs = more(spark, [line + "\nother " + long, "first\n" + line.upper() + "\nlast. " + long + " end", "One two three."], 1)
    got = {r.doc_id: r for r in substring_dedup.dedup(docs, substring_dedup.BOTH).collect()}
    assert {i: bytes(r.kept).decode() for i, r in got.items()} == {1: line + "\nother " + long, 2: "first\nlast. " + long + " end", 3: "One two three."}
    assert (got[2].n_units, got[2].n_removed, [tuple(s) for s in got[2].removed]) == (7, 3, [(6, 6 + len(line) + 1)])
    again = more(spark, ["x " + long + "\n" + long, "y. " + long + " z"], 1)
    assert bytes(substring_dedup.dedup(again, substring_dedup.BOTH).where("doc_id = 2").first().kept).decode() == "y. z"


def test_components_of_chains_and_stars(spark):
    chain = [(i, i + 1) for i in range(100, 160)]
    star = [(7, i) for i in range(200, 240)]
    got = {r.node: r.component for r in engine.components(spark.createDataFrame([*chain, *star, (5, 5), (None, 3)], "a long, b long"), spark.createDataFrame([(1,), (100,)], "node long")).collect()}
    assert got == {**{i: 100 for i in range(100, 161)}, **{i: 7 for i in [7, *range(200, 240)]}, 1: 1}


def test_components_of_edges_that_differ_when_computed_again(spark):
    """A spanning forest that depends on what arrives first: whichever one is read, one component comes out."""

    def forest(batches):
        import random

        import pyarrow as pa

        for b in batches:
            nodes = b.column(0).to_pylist()
            random.shuffle(nodes)
            yield pa.RecordBatch.from_arrays([pa.array(nodes[:-1], pa.int64()), pa.array(nodes[1:], pa.int64())], ["a", "b"])

    got = engine.components(spark.range(0, 200, 1, 1).mapInArrow(forest, "a long, b long")).collect()
    assert len(got) == 200 and {r.component for r in got} == {0}


def test_toxicity_chain_held_out():
    rng = np.random.default_rng(0)
    vocab = [f"w{i}" for i in range(300)]
    bad = ["vile0", "vile1", "vile2"]

    def sample(n):
        texts, y = [], []
        for _ in range(n):
            w, kind = list(rng.choice(vocab, 40)), rng.random()
            if kind < 0.5:  # toxic texts are those with a bad word that are not junk
                w[3], w[9] = rng.choice(bad, 2)
            if 0.3 < kind < 0.7:
                w[5], w[6] = "junk1", "junk2"
            texts.append(" ".join(w).encode())
            y.append((int(0.3 < kind < 0.7), int(kind < 0.3)))
        return texts, y

    chain = toxicity.fit(*sample(1500))
    import pyarrow as pa

    texts, y = sample(600)
    p = toxicity._scores(pa.record_batch([pa.array([t.decode() for t in texts])], ["text"]), chain, "text")
    y = np.array(y)[:, 1]
    hit = p[:, -1] >= toxicity.THRESHOLD
    assert chain.weights[1][-2] < 0  # junk speaks against toxic
    assert y[hit].mean() > 0.97 and hit[y > 0].mean() > 0.97
    assert toxicity.fit([b"a", b"b"], [(0, 0), (0, 0)]).predict(np.zeros(0, np.uint64), np.zeros(0, np.int64), 1).max() < 0.01
    assert toxicity.fit([], []).predict(np.zeros(0, np.uint64), np.zeros(0, np.int64), 1).max() < 0.01
    out_of_fold = chain.held_out["toxic"]
    assert out_of_fold["precision"] > 0.95 and out_of_fold["recall"] > 0.95


def test_toxicity_on_odd_rows(spark):
    docs = more(spark, ["you idiot trash moron", "", None, "fine words", "w " * 300_000])
    docs = docs.unionByName(docs.limit(1).withColumn("doc_id", F.lit(None).cast("long"))).withColumns({c: F.lit(1) for c in ("_id", "_y", "_doc", "toxic", "rejected")})
    labels = spark.createDataFrame([(10**6, 1, 1), (10**6 + 3, 1, 0), (None, 1, 1)], "doc_id long, quality int, toxic int")
    chain = toxicity.train(docs, labels)
    assert toxicity.score(docs, chain).count() == 6 and toxicity.score(docs, chain).columns == ["doc_id", "low_quality", "toxic", "rejected"]
    assert toxicity.score(docs.where("false"), chain).count() == 0 and toxicity.accept(docs.where("false"), chain).columns == docs.columns
    assert set(toxicity.accept(docs.withColumn("extra", docs.doc_id), chain).columns) == {*docs.columns, "extra"}
    assert toxicity.accept(docs, toxicity.train(docs, labels.where("false"))).count() == 6


def test_mixing_meets_targets(spark):
    docs = more(spark, ["a b c d"] * 400 + ["e f g h"] * 40 + ["i j k l"] * 4 + [None, "  "], 0)
    docs = docs.selectExpr("doc_id", "text", "case when doc_id < 400 then 'x' when doc_id < 440 then 'y' else 'z' end as source")
    tokens = docs.select("source", mixing.token_count(docs.text).alias("n_tokens"))
    w = {r.source: r for r in mixing.source_weights(tokens, 0.6, None).collect()}
    assert abs(mixing.entropy([r.weight for r in w.values()]) - 0.6 * np.log(3)) < 1e-6
    w = {r.source: r for r in mixing.source_weights(tokens, 0.9, 3.0).collect()}
    assert max(r.budget / r.tokens for r in w.values()) <= 3.0 + 1e-6
    drawn = mixing.mix(docs, 0.6, None, blocks=64).groupBy("source").sum("n_tokens").collect()
    plan = {r.source: r.budget for r in mixing.source_weights(tokens, 0.6, None).collect()}
    for r in drawn:
        assert abs(r[1] - plan[r.source]) <= 0.5 * 40 + 4
    assert mixing.solve_exponent([], 0.9, 4.0, 0) == 1.0 and mixing.solve_exponent([5], 0.9, 4.0, 5) == 1.0
    assert mixing.mix(docs.where("false")).count() == 0
    odd = docs.unionByName(docs.selectExpr("cast(null as long) as doc_id", "text", "cast(null as string) as source").limit(3)).withColumns({c: F.lit(1) for c in ("block", "s", "b", "pass", "tokens", "n_tokens")})
    one, two = (sorted(map(tuple, mixing.mix(odd, 0.6, None, blocks=8, keep=("text",), broadcast_rows=n).collect()), key=str) for n in (10**6, 0))
    assert one == two and len(one) > 400 and all(r[2] > 0 and r[-1].strip() for r in one) and sum(r[0] is None for r in one) >= 3


def test_url_lists(spark):
    import datetime as dt

    day = lambda n: dt.date(2024, 1, 1) + dt.timedelta(n)
    feed = [("host", "a.b.com", "add", 10, "x"), ("host", "a.b.com", "add", 12, "x"), ("host", "a.b.com", "remove", 20, "x"), ("host", "A.b.com", "add", 30, "x"), ("domain", "b.com", "add", 15, None), ("prefix", "c.org/p", "add", 0, "y"), ("prefix", "c.org/p", "remove", 0, "y"), ("host", None, "add", 1, "x"), ("domain", "b.com", "add", 15, None)]
    entries = spark.createDataFrame([(k, x, a, day(d), c) for k, x, a, d, c in feed], "kind string, key string, action string, day date, category string")
    urls = ["https://a.b.com/q", "http://A.B.com:80/p?x", "http://b.com", "http://c.org/p/1", "nonsense", None, "ftp://x.notb.com/"]
    caps = [(i * 100 + d, u, day(d)) for i, u in enumerate(urls) for d in (0, 10, 14, 16, 19, 20, 29, 30)] + [(9999, urls[0], None)]
    captures = spark.createDataFrame(caps, "page_id long, url string, fetched date")

    def brute(u, d):
        out = []
        host = re.match(r"[a-z]+://([^/?#:]+)", (u or "").lower())
        if host and d is not None:
            h = host[1]
            if h == "a.b.com" and (day(10) <= d < day(20) or d >= day(30)):
                out.append("host:a.b.com:x")
            if (h == "b.com" or h.endswith(".b.com")) and d >= day(15):
                out.append("domain:b.com:listed")
        return ",".join(sorted(out))

    want = {i: brute(u, d) for i, u, d in caps}
    for limit in (100, 0):
        got = {r.page_id: r.rules for r in url_lists.evaluate(captures, entries, broadcast_rows=limit).collect()}
        assert got == want
    assert not url_lists.evaluate(captures, entries.where("false")).where("blocked").count()


def test_feed_lists_hot_parent_domains(spark):
    pages = spark.createDataFrame([(i, f"https://h{i}.example.org/p{i}") for i in range(300)], "page_id long, url string")
    feed = url_lists.derived_feed(pages)
    assert feed.where("kind = 'domain' and key = 'example.org'").count()
    met = url_lists.evaluate(url_lists.dated_captures(pages), feed).where("rules like '%domain:example.org:%'").count()
    since = {r.day for r in feed.where("kind = 'domain' and key = 'example.org' and action = 'add'").collect()}
    assert met and since and met <= 300


def test_training_text_is_drawn_by_id_hash(spark, monkeypatch):
    monkeypatch.setattr(toxicity, "fit", lambda texts, toxic, names: tuple(texts))
    docs = spark.createDataFrame([(0, "long " * 180_000), *((i, f"{i} " + "x" * 4000) for i in range(1, 401))], "doc_id long, text string")
    labels = docs.select("doc_id").selectExpr("doc_id", "1 as quality", "0 as toxic")
    seen = {int(t.split()[0]) for t in toxicity.train(docs, labels, max_mb=1) if t[:4] != b"long"}
    assert len(seen) > 250 and max(seen) > 350


def test_pipeline(spark):
    """The whole output against brute force: lines, classes and benchmark words, then the mixture of what is left."""
    import corpus_pipeline
    from test_scans import brute_contamination

    out = corpus_pipeline.run(spark, SF)
    docs, bench = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "benchmark"))
    chain = toxicity.train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    bad = {r.doc_id for r in toxicity.score(docs, chain).where("rejected").collect()}
    given_ = {r.doc_id: r for r in docs.collect()}
    gone = brute_lines([(i, r.text) for i, r in given_.items() if i not in bad])
    rows = [(i, "\n".join(x for k, x in enumerate(given_[i].text.split("\n")) if k not in gone[i])) for i in gone]
    classes = brute_classes(rows)
    rows = [(i, t) for i, t in rows if classes[i][1] == i]
    hit = brute_contamination(rows, [(r.item_id, r.text) for r in bench.collect()])
    rows = [(i, t, given_[i].source, given_[i].lang) for i, t in rows if not hit[i][4]]
    want = mixing.mix(spark.createDataFrame(rows, "doc_id long, text string, source string, lang string"), keep=("text", "lang"))
    assert sorted(out.columns) == sorted(want.columns)
    key = lambda r: (r.doc_id, r["pass"], r.position, r.block, r.text, r.lang, r.source, r.n_tokens)
    got = sorted(map(key, out.collect()))
    assert got == sorted(map(key, want.collect())) and len(got) > 100 and all(r[-1] > 0 for r in got)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line dedup", "ngram jaccard join", "decontamination", "mixing"]


def test_pipeline_stages_on_odd_tables(spark, tmp_path):
    """Every stage on an empty table and on one with null, empty, repeated and clashing values; labels and benchmark are empty or given."""
    import corpus_pipeline

    docs = spark.createDataFrame([(None, None, None, None, None), (1, "", "en", "s", 0), (1, BASE, "en", None, 5), (1, BASE, "en", None, 5), (2, BASE, None, "s", 5), (3, None, "en", "s", 0)], "doc_id long, text string, lang string, source string, n_chars long")
    docs = docs.withColumns({c: F.lit("x") for c in ("_id", "_removed", "_drop", "tag", "th", "d", "t", "block", "pass", "_y")})
    given(spark).write.parquet(f"{tmp_path}/documents.parquet")
    spark.read.parquet(f"{SF}/labels.parquet").limit(0).write.parquet(f"{tmp_path}/labels.parquet")
    spark.read.parquet(f"{SF}/benchmark.parquet").limit(0).write.parquet(f"{tmp_path}/benchmark.parquet")
    for name, stage in corpus_pipeline.STAGES:
        for sf in (SF, str(tmp_path)):
            empty = stage(spark, docs.where("false"), sf)
            some = stage(spark, docs, sf).collect()
            assert empty.count() == 0 and (name == "mixing" or (empty.columns == docs.columns and len(some) == {"ngram jaccard join": 5}.get(name, 6)))
