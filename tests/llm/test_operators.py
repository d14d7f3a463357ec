"""The training-data operators on small tables: brute force, round trips, edge cases."""

import hashlib
import random
import re
import zlib
from collections import Counter
from math import comb

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from tidelabel.llm import bpe, components, language, line_dedup, minhash, packing, quality_model, quality_rules, sharding, toxicity, vectors
from tidelabel.llm.common import documents

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, h string, at int, words string"
WORD = re.compile("[^\x20\x09-\x0D]+")


def frame(spark, texts, **more):
    rows = [(i, t, more.get("lang", ["en", "de"])[i % 2], more.get("source", f"s{i % 3}"), len(t or ""), "x", 1, "w") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, SCHEMA)


ODD = [None, "", " \n\t ", "a", "a", "word " * 30_000, "x" * 60_000, "one two three four five six", "ÀÉ ñ 中文 😀 <|endoftext|> it's 12", "\x1c\x85   \n\n y"]


@pytest.fixture(scope="module")
def odd(spark):
    return frame(spark, ODD)


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(bpe.default_vocabulary())


# BPE
def test_bpe_equals_the_library(spark, odd, library):
    rng = random.Random(4)
    pool = [chr(c) for c in range(0x600)] + list("   \n\n'stremll09aAbBéß") * 30 + ["<|endoftext|>", "中", " ", "é"] * 4
    texts = ODD + ["".join(rng.choices(pool, k=rng.randint(0, 50))) for _ in range(300)]
    got = {r.doc_id: r for r in bpe.token_digests(frame(spark, texts)).collect()}
    ids = {r.doc_id: r.ids for r in bpe.encode_documents(frame(spark, texts)).collect()}
    back = {r.doc_id: r.text for r in bpe.decode_documents(bpe.encode_documents(frame(spark, texts))).collect()}
    for i, t in enumerate(texts):
        want = library.encode(t or "", add_special_tokens=False).ids
        assert ids[i] == want and back[i] == (t or "")
        assert got[i].n_tokens == len(want) and got[i].ids_sha256 == hashlib.sha256(",".join(map(str, want)).encode()).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256(library.decode(want, skip_special_tokens=False).encode()).hexdigest()


def test_pairs_stand_as_merging_says():
    v = bpe.vocabulary(bpe.default_vocabulary())
    assert all(next(v.encode_words([b]))[1] == [i] for b, i in list(v.id_of.items())[::97])


# packing
def checked_pieces(rows, ids, window):
    by_doc, by_seq = {}, {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_seq.setdefault(r.sequence_id, []).append(r)
    for i, want in ids.items():
        at = 0
        for r in sorted(by_doc[i], key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(want)
            assert r.ids_crc32 == zlib.crc32(np.array(want[at : at + r.length], dtype="<u4").tobytes())
            at += r.length
        assert at == len(want)
    for s, pieces in by_seq.items():
        at = 0
        for r in sorted(pieces, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at == window or s == max(by_seq)
    assert sorted(by_seq) == list(range(len(by_seq)))


@pytest.mark.parametrize("window,quantum", [(1024, 64), (64, 64), (100, 7)])
def test_packing_is_exact(spark, odd, library, window, quantum):
    rows = packing.pack(odd.repartition(3), window=window, quantum=quantum).collect()
    ids = {i: library.encode(t or "", add_special_tokens=False).ids + [0] for i, t in enumerate(ODD)}
    checked_pieces(rows, ids, window)


def test_packing_serves_as_a_deficit_round_robin(spark):
    """Closed-form places against serving quanta one by one."""
    totals, weights, q = np.array([1000, 90, 333]), np.array([7, 2, 5]), 16
    order = sorted((i / w, s, i) for s, (t, w) in enumerate(zip(totals, weights)) for i in range(1, -(-t // q) + 1))
    at, want = 0, {}
    from fractions import Fraction

    order = sorted((Fraction(i, int(weights[s])), s, i) for _, s, i in order)
    for _, s, i in order:
        want[s, i] = at
        at += min(q, totals[s] - (i - 1) * q)
    keys = list(want)
    got = packing.service_start(np.array([k[0] for k in keys]), np.array([k[1] for k in keys]), totals, weights, q)
    assert got.tolist() == [want[k] for k in keys]


def test_windows_hold_the_target_mixture(spark):
    docs = frame(spark, ["alpha beta gamma delta " * 40] * 60)
    rows = packing.mixture(packing.pack(docs, targets={"s0": 2, "s1": 1, "s2": 1}, quantum=16)).where("sequence_id < 5").collect()
    for r in rows:
        assert abs(r.tokens - 1024 * (0.5 if r.source == "s0" else 0.25)) <= 32


def test_empty_tables(spark):
    none = spark.createDataFrame([], SCHEMA)
    assert packing.pack(none).count() == 0 and minhash.near_groups(none).count() == 0 and line_dedup.duplicate_lines(none).count() == 0
    assert bpe.token_digests(none).count() == 0 and language.identify(none, language.learn(none)).count() == 0
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert quality_rules.quality_rules(none, labels).count() == 0
    assert toxicity.score(none, toxicity.train(none, labels)).count() == 0
    assert vectors.nearest(*[vectors.usable(spark.createDataFrame([], "vec_id long, embedding array<float>"))] * 2, 3).count() == 0


# near duplicates
def brute_groups(texts, percent=75):
    low = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    sets = []
    for t in texts:
        w = WORD.findall((t or "").translate(low))
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    parent = list(range(len(sets)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(sets)):
        for j in range(i):
            if sets[i] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
    return {i: (len(s), root(i)) for i, s in enumerate(sets)}


def varied(rng, base, n):
    words = base.split()
    for _ in range(n):
        words[rng.randrange(len(words))] = f"w{rng.randrange(10**6)}"
    return " ".join(words)


def test_rows_that_share_an_id_are_linked_by_their_texts(spark):
    text = lambda seed, n=60: " ".join(random.Random(seed).choices("abcdefghijklmnop", k=n))
    rows = [(5, text(1)), (5, text(2)), (2, text(2) + " z"), (7, text(3)), (7, text(3)), (None, text(1)), (9, None), (9, text(3) + " q")]
    docs = spark.createDataFrame([(d, t, i, i) for i, (d, t) in enumerate(rows)], "doc_id long, text string, spot int, number int")
    groups = minhash.near_groups(docs)
    got = sorted(((r.doc_id, r.component_id, r.kept, r.n_shingles > 0) for r in groups.collect()), key=str)
    want = [(5, 5, True, True), (5, 2, False, True), (2, 2, True, True), (7, 7, True, True), (7, 7, True, True), (None, 5, False, True), (9, 9, True, False), (9, 7, False, True)]
    assert got == sorted(want, key=str)
    left = minhash.one_of_each(docs, groups)
    assert left.columns == docs.columns
    kept = sorted(r.spot for r in left.collect())
    assert kept in ([0, 2, 3, 6], [0, 2, 4, 6])


def test_near_groups_equal_brute_force(spark):
    rng = random.Random(9)
    vocabulary = [f"t{i}" for i in range(300)]
    base = [" ".join(rng.choices(vocabulary, k=rng.randint(60, 120))) for _ in range(8)]
    texts = ODD + [varied(rng, rng.choice(base), rng.randint(0, 6)) for _ in range(250)] + base[:2] * 3
    passage = " ".join(rng.choices(vocabulary, k=60))
    texts += [passage + " " + " ".join(rng.choices(vocabulary, k=30)) for _ in range(60)]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash.near_groups(frame(spark, texts)).collect()}
    assert got == brute_groups(texts)


def test_chains_of_near_copies_are_one_group(spark):
    words = [f"u{i}" for i in range(100)]
    texts = []
    for k in range(20):
        words = words[:]
        words[5 * k % 100] = f"new{k}"
        texts.append(" ".join(words))
    got = {r.doc_id: r.component_id for r in minhash.near_groups(frame(spark, texts)).collect()}
    assert got == {i: c for i, (_, c) in brute_groups(texts).items()}


def test_super_minhash_estimates_similarity():
    rng = np.random.default_rng(3)
    a = rng.integers(0, 1 << 63, 400, dtype=np.uint64)
    b = np.concatenate([a[:300], rng.integers(0, 1 << 63, 100, dtype=np.uint64)])
    errors = []
    for k in range(30):
        s = minhash.signatures([np.unique(a + np.uint64(k)), np.unique(b + np.uint64(k))], 128)
        errors.append((s[0] == s[1]).mean() - 0.6)
        assert (s < np.uint64(128) << np.uint64(32)).all()
    assert abs(np.mean(errors)) < 0.03


@pytest.mark.parametrize("one_task", [0, 500_000])
def test_components_equal_union_find(spark, monkeypatch, one_task):
    monkeypatch.setattr(components, "ONE_TASK_LINKS", one_task)
    rng = random.Random(1)
    links = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(400, 460)]
    parent = {}

    def root(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in links:
        if a != b:
            p, q = root(a), root(b)
            parent[max(p, q)] = min(p, q)
    got = {r.id: r.component for r in components.connected(spark.createDataFrame(links, "a long, b long").repartition(7)).collect()}
    assert got == {x: root(x) for x in parent}


# lines
def test_duplicate_lines_equal_the_twin(spark, sf_dir):
    con = duckdb.connect()
    con.execute(f"create view documents as select * from read_parquet('{sf_dir}/documents.parquet')")
    ours = {tuple(r) for r in line_dedup.op7_deletion_lines(spark, sf_dir).collect()}
    assert ours == set(con.execute(line_dedup.ORACLE).fetchall())


def within_one(a, b):
    if abs(len(a) - len(b)) > 1:
        return False
    i = 0
    while i < min(len(a), len(b)) and a[i] == b[i]:
        i += 1
    j = 0
    while j < min(len(a), len(b)) - i and a[-1 - j] == b[-1 - j]:
        j += 1
    return i + j >= max(len(a), len(b)) - 1


def test_duplicate_lines_equal_brute_force(spark):
    rng = random.Random(2)
    lines, out = [], []
    for _ in range(400):
        if lines and rng.random() < 0.5:
            w = rng.choice(lines).split()
            for _ in range(rng.choice([0, 1, 1, 2])):
                k, i = rng.randrange(3), rng.randrange(len(w))
                w[i : i + 1] = [[], ["zz"], ["yy", w[i]]][k if len(w) > 1 else 1]
            lines.append(" ".join(w))
        else:
            lines.append(" ".join(rng.choices("abcdef", k=rng.randint(1, 14))))
    texts = ["\n".join(lines[i : i + 8]) for i in range(0, 400, 8)]
    seen = []
    for d, t in enumerate(texts):
        for n, line in enumerate(t.split("\n")):
            w = WORD.findall(line)
            first = next(((p, int(v != w)) for v, p in seen if v == w), None)
            near = next((p for v, p in seen if min(len(w), len(v)) >= 3 and within_one(v, w)), None) if len(w) >= 3 else None
            if near is not None and (first is None or near < first[0]):
                out.append((d, n, *near, 1))
            elif first is not None:
                out.append((d, n, *first[0], 0))
            seen.append((w, (d, n)))
    got = line_dedup.duplicate_lines(frame(spark, texts)).collect()
    assert {(r.doc_id, r.line_no, r.first_doc_id, r.first_line_no, r.edits) for r in got} == set(out)


def test_rows_that_share_an_id_lose_their_own_lines_only(spark):
    """Clashing column names, a null id and equal ids; white space of all kinds; a very long line."""
    far = " ".join(f"w{i}" for i in range(20_000))
    rows = [
        (5, "first here\nshared by two rows of one id", 0), (5, "second there\nshared\tby  two rows of one id", 1), (5, "only in this\nnot in the other row at all", 2),
        (None, "not in the other row at all", 3), (7, far, 4), (8, far + " w", 5), (9, "alone stays", 6), (9, None, 7), (-3, "alone stays\nand more", 8),
    ]
    docs = spark.createDataFrame([(d, t, n, n, n, n, n, n) for d, t, n in rows], "doc_id long, text string, removed int, owner int, owner_key int, bits int, bits_row int, line_hash int")
    dups = line_dedup.duplicate_lines(docs)
    assert {(r.doc_id, r.line_no, r.first_doc_id, r.first_line_no, r.edits) for r in dups.collect()} == {(5, 1, None, 0, 0), (8, 0, 7, 0, 1), (9, 0, -3, 0, 0)}
    left = line_dedup.without_duplicate_lines(docs, dups)
    assert left.columns == docs.columns
    assert {r.removed: r.text for r in left.collect()} == {0: rows[0][1], 1: rows[1][1], 2: "only in this", 3: rows[3][1], 4: far, 7: None, 8: rows[8][1]}


def test_lines_leave_clean_documents_alone(spark, odd):
    texts = ODD + ["only this line is here today\nand one that is used again and again ok", "new words only in this one\nand one that is used again and again ok"]
    docs = frame(spark, texts)
    left = {r.doc_id: r for r in line_dedup.without_duplicate_lines(docs, line_dedup.duplicate_lines(docs)).collect()}
    assert left[11].text == "new words only in this one" and left[11].n_chars == 26 and left[10].text == texts[10] and set(left) == set(range(12)) - {4}


# quality
def signals(t):
    t = t or ""
    w = WORD.findall(t)
    c = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    covered = {j for i in range(len(w) - 4) if c[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(covered)


def test_quality_measures_equal_plain_python(spark, odd):
    labels = spark.createDataFrame([(0, 1), (3, 0)], "doc_id long, quality int")
    for r in quality_rules.quality_rules(odd, labels).collect():
        n = signals(ODD[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == n
        assert r.base_failed == (n[0] < 10 or 100 * n[4] > 20 * n[0]) and r.kept == (not r.base_failed)


def test_binomial_tails(spark):
    pairs = [(k, n) for n in (1, 5, 50, 400, 3000) for k in (0, 1, 3, 9) if k <= n * 0.02]
    for r in spark.createDataFrame(pairs, "k long, n long").withColumn("t", quality_rules.binomial_tail("k", "n", 0.02)).collect():
        assert r.t == pytest.approx(sum(comb(r.n, i) * 0.02**i * 0.98 ** (r.n - i) for i in range(r.k + 1)), rel=1e-9)


def test_cutoffs_bound_false_rejections(spark):
    rng = np.random.default_rng(0)
    rows = [("a", int(q), int(s * 100), 100, 0, 1, 0, 100, 60) for q, s in zip(rng.random(4000) < 0.8, rng.random(4000) * 0.2)]
    rows = [(*r[:2], r[2] + (0 if r[1] else 60), *r[3:]) for r in rows]
    holdout = spark.createDataFrame(rows, "stratum string, quality int, n_symbols int, word_chars int, n_dup_lines int, n_lines int, n_repeat_words int, n_words int, n_distinct int")
    cut = quality_rules.cutoffs(holdout).first()
    assert cut.cut_symbol_share is not None
    good = [r[2] / 100 for r in rows if r[1]]
    assert np.mean([g > cut.cut_symbol_share for g in good]) <= quality_rules.RISK


def test_cutoffs_of_small_strata_bound_all_rules_together(spark):
    """300 good rows give cutoffs; rules that would each lose 1 % of the good rows don't add up."""
    rng = np.random.default_rng(5)
    names = "stratum string, quality int, n_symbols int, word_chars int, n_dup_lines int, n_lines int, n_repeat_words int, n_words int, n_distinct int"
    rows = [(s, 1, int(rng.integers(0, 20)), 100, 0, 1, 0, 20, 15) for s in "abcd" for _ in range(300)] + [(s, 0, 60, 100, 0, 1, 0, 20, 15) for s in "abcd" for _ in range(30)]
    cuts = {r.stratum: r for r in quality_rules.cutoffs(spark.createDataFrame([(*r, i) for i, r in enumerate(rows)], names + ", doc_id long")).collect()}
    assert set(cuts) == set("abcd") and all(0.19 <= c.cut_symbol_share < 0.6 for c in cuts.values())
    n = rng.integers(0, 1000, (5000, 3))
    holdout = spark.createDataFrame([("a", int(i % 5 > 0), int(x), 1000, int(y), 1000, 0, 1000, int(z), i) for i, (x, y, z) in enumerate(n)], names + ", doc_id long")
    lost = quality_rules.judged(holdout, quality_rules.cutoffs(holdout)).where("quality = 1")
    assert lost.where("not kept").count() <= quality_rules.RISK * lost.count()


def test_ordinal_thresholds_are_ordered_and_grades_found():
    rng = np.random.default_rng(1)
    grades = rng.integers(0, 3, 300)
    examples = [(np.array([g + 1, 10 + i % 5]), np.array([1.0, 0.3])) for i, g in enumerate(grades)]
    m = quality_model.fit(examples, grades)
    tails = np.array([m.tails(*e) for e in examples])
    assert (np.diff(m.thresholds) > 0).all() and (tails[:, 0] >= tails[:, 1]).all()
    assert ((tails > 0.5).sum(axis=1) == grades).mean() > 0.95
    assert quality_model.fit([], np.array([], int)).tails(np.array([1]), np.array([1.0])) == pytest.approx([2 / 3, 1 / 3])


def test_grades_of_tables(spark, odd):
    """Nulls, empty and long texts, repeated ids, extra columns, an empty table; the same fit whatever the partitions."""
    good, bad = "a calm report on the river and its mills", "xx !! buy now $$$ buy now $$$"
    docs = frame(spark, [good + f" {i}" if i % 2 else bad + f" {i}" for i in range(120)])
    rated = docs.select("doc_id", "text", F.when(F.col("doc_id") % 2 == 1, 2).otherwise(0).alias("grade"))
    model, again = quality_model.train(rated), quality_model.train(rated.union(rated.limit(0)).repartition(7))
    assert (model.weights == again.weights).all() and (model.thresholds == again.thresholds).all()
    got = {r.doc_id: r for r in quality_model.grade(docs, model).collect()}
    assert all(r.kept == (i % 2 == 1) and abs(r.expected_grade - r.p_ge_1 - r.p_ge_2) < 1e-12 for i, r in got.items())
    strange = quality_model.grade(odd.union(odd), model).collect()
    assert len(strange) == 2 * len(ODD) and all(0 <= r.p_ge_2 <= r.p_ge_1 <= 1 for r in strange)
    none = rated.where("doc_id < 0")
    assert quality_model.grade(none, quality_model.train(none)).count() == 0
    assert {round(r.expected_grade, 6) for r in quality_model.grade(odd, quality_model.train(none)).collect()} == {1.0}


# classifiers
def test_language_of_held_out_documents(spark, sf_dir):
    found = language.op1_language(spark, sf_dir).join(documents(spark, sf_dir).select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r.lang == r.lang_pred for r in found]) > 0.97 and all(0 <= r.score <= 1 for r in found)


def test_language_of_odd_texts(spark, odd, sf_dir):
    filters = language.learn(documents(spark, sf_dir).select("lang", "text"))
    got = {r.doc_id: r for r in language.identify(odd, filters).collect()}
    assert all((got[i].lang_pred, got[i].score) == ("und", 0.0) for i in (0, 1, 2)) and got[7].lang_pred in filters.names


def gram_hash(gram):
    mask = (1 << 64) - 1

    def mix(x):
        x = (x ^ (x >> 30)) * 0xBF58476D1CE4E5B9 & mask
        x = (x ^ (x >> 27)) * 0x94D049BB133111EB & mask
        return x ^ (x >> 31)

    key = len(gram) * 0x9E3779B97F4A7C15 & mask
    for i, c in enumerate(gram):
        key = mix((key + ord(c)) & mask) if i == 2 else (key * 0x9E3779B97F4A7C15 + ord(c)) & mask
    return mix(key) >> 1


def grams_of(text):
    for w in re.findall(r"[^\W\d_]+", (text or "").lower()):
        w = f" {w} "
        yield from (w[i : i + n] for n in language.SIZES for i in range(len(w) - n + 1) if n > 1 or w[i] != " ")


def test_filters_and_counts_equal_brute_force(spark, sf_dir):
    """Counts of n-grams, the filters' bits, and popcounts by text, against plain Python."""
    texts = [r.text for r in documents(spark, sf_dir).limit(40).collect()] + ODD + ["İstanbul ǅ ²³ x_y 中文字 aßb", "I"]
    langs = [["aa", "bb", "cc"][i % 3] for i in range(len(texts))]
    rows = spark.createDataFrame(list(zip(langs, texts)), "lang string, text string").repartition(3)
    want = {}
    for lang, t in zip(langs, texts):
        for g in grams_of(t):
            want[lang, gram_hash(g)] = want.get((lang, gram_hash(g)), 0) + 1
    assert {(r.lang, r.gram): r.n for r in language.gram_counts(rows).collect()} == want
    total = {x: sum(n for (lang, _), n in want.items() if lang == x) for x in set(langs)}
    share = {k: n / total[k[0]] for k, n in want.items()}
    best = {}
    for (_, g), x in share.items():
        best[g] = max(best.get(g, 0), x)
    slots = lambda g: [(g + i * (g >> 32)) % language.SLOTS for i in range(language.HASHES)]
    filters = language.learn(rows)
    held = {x: set() for x in total}
    for (lang, g), x in share.items():
        if x >= language.RARE and x >= language.NEAR * best[g]:
            held[lang].update(slots(g))
    assert filters.names == sorted(total, key=lambda x: (-total[x], x))
    for i, lang in enumerate(filters.names):
        assert set(np.flatnonzero((filters.slots[0] >> i) & 1).tolist()) == held[lang]
    got = language.Reader(filters).predict(texts)
    for t, (lang, score, known) in zip(texts, got):
        grams = [gram_hash(g) for g in grams_of(t)]
        hits = np.array([sum(all(s in held[x] for s in slots(g)) for g in grams) for x in filters.names], dtype=float)
        right = np.maximum(hits - len(grams) * filters.chance, 0) / (1 - filters.chance)
        if not any(c.isalpha() for c in t or ""):
            assert (lang, score, known) == ("und", 0.0, 0.0)
        else:
            assert lang == filters.names[int(right.argmax())] and abs(score - right.max() / max(right.sum(), 1e-300)) < 1e-9 and abs(known - min(right.max() / len(grams), 1)) < 1e-9


def test_toxicity_on_held_out_documents(spark):
    d = "/root/testdata/sf0.01"
    found = toxicity.op9_kneser_ney(spark, d).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id").where("held_out").collect()
    toxic = [r.predicted for r in found if r.toxic == 1]
    assert np.mean(toxic) > 0.7 and np.mean([r.predicted for r in found if r.toxic == 0]) < 0.03
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in found)


def test_toxicity_without_labels_and_of_odd_texts(spark, odd):
    none = odd.select("doc_id", F.lit(0).alias("toxic")).where("doc_id < 0")
    rows = toxicity.score(odd, toxicity.train(odd, none)).collect()
    assert len(rows) == len(ODD) and all(r.score < 0.01 and r.predicted == 0 for r in rows)


def test_word_pairs_dont_share_counts(spark):
    """Pairs of words that fell into one slot of 2,097,143 are told apart, unseen ones say nothing."""
    import xxhash

    words = [f"q{i}" for i in range(2000)]
    slot = np.array([1 + xxhash.xxh3_64_intdigest(w.encode()) % ((1 << 21) - 1) for w in words], dtype=np.int64)
    at = (slot[0] * (1 << 21) + slot[1]) % 2_097_143
    i, j = next((i, j) for i, j in zip(*np.nonzero((slot[:, None] * (1 << 21) + slot) % 2_097_143 == at)) if i > 1 and j > 1)
    docs = frame(spark, [f"n{k} q0 q1" for k in range(60)] + [f"n{k} q1 q0" for k in range(60)])
    labels = docs.select("doc_id", (F.col("doc_id") < 60).cast("int").alias("toxic"))
    model = toxicity.train(docs, labels)
    say = lambda text: toxicity.Reader(model).evidence(text)
    assert say("q0 q1")[0] > 0 > say("q1 q0")[0] and say(f"{words[i]} {words[j]}") == (0.0, 0.0)


def test_toxicity_model_equals_plain_python(spark):
    """Counts, levels and evidence against dictionaries of strings."""
    from collections import Counter
    from math import log

    rng = np.random.default_rng(5)
    plain, abuse = [f"wort{i}" for i in range(12)], ["grimble", "grimbles", "snark"]
    texts = [" ".join(rng.choice(plain + (abuse if k % 3 == 0 else abuse[2:] if k % 20 == 1 else []), 14)) for k in range(240)] + [None, "", "...", "snark"]
    label = [int(k % 3 == 0) for k in range(len(texts))]
    rows = spark.createDataFrame([(label[k], texts[k]) for k in range(len(texts))], "toxic int, text string")
    made = toxicity.kneser_ney(toxicity.counts(rows).where(f"second = 0 or greatest(toxic, other) > {toxicity.DISCOUNT}"))
    model = toxicity.Model(**made, weights=np.zeros(3))

    parts = lambda w: [w] + [w[:n] + "*" for n in toxicity.BEGINNINGS if n < len(w)]
    unit, pair = [Counter(), Counter()], [Counter(), Counter()]
    for c, text in zip(label, texts):
        words = toxicity.words_of(text)
        unit[c].update({u for w in words for u in parts(w)})
        pair[c].update(set(zip(words, words[1:])))
    d, total = toxicity.DISCOUNT, [sum(unit[0].values()), sum(unit[1].values())]
    seen = lambda u: (unit[0][u] > 0) + (unit[1][u] > 0)
    every = set(unit[0]) | set(unit[1])
    back = sum(min(unit[c][u], d) for u in every for c in (0, 1)) / sum(total)
    p = [{u: max(unit[c][u] - d, 0) / total[c] + back * seen(u) / sum(map(seen, every)) for u in every} for c in (0, 1)]

    def sure(n, of):
        return 2 * sum(n[c] * log(n[c] * sum(of) / (of[c] * sum(n))) for c in (0, 1) if n[c]) >= toxicity.SURE**2

    says = {u: log(p[1][u] / p[0][u]) for u in every if sure([unit[0][u], unit[1][u]], total)}
    pairs = {}
    for a, b in set(pair[0]) | set(pair[1]):
        n, of = [pair[0][a, b], pair[1][a, b]], [max(unit[0][a], 1), max(unit[1][a], 1)]
        if max(n) > d and sure(n, of):
            q = [min(max(n[c] - d, 0) / of[c], 1) + max(min(d / sum(of), 1), 1e-6) * p[c][b] for c in (0, 1)]
            pairs[a, b] = log(q[1] / q[0])
    assert len(model.units) == len(says) > 0 and len(model.pairs) == len(pairs)

    reader = toxicity.Reader(model)
    for text in [*texts, "grimblest snark wort1", "unseen words"]:
        words = toxicity.words_of(text)
        r = [next((says[u] for u in parts(w) if u in says), 0.0) for w in words]
        r = [pairs.get((words[i - 1], w), r[i]) if i else r[i] for i, w in enumerate(words)]
        r = [min(max(x, toxicity.LEAST), toxicity.MOST) for x in r]
        width = min(toxicity.STRETCH, len(r))
        want = (sum(r) / len(r), max(sum(r[i : i + width]) for i in range(len(r) - width + 1)) / toxicity.STRETCH) if r else (0.0, 0.0)
        assert np.allclose(reader.evidence(text), want, atol=1e-5)


def test_toxicity_words_are_learned_anew_after_being_forgotten(monkeypatch):
    keys = np.array(sorted(toxicity.unit_key(w) for w in ("bad", "good")), dtype=np.uint64)
    unit = np.array([1.5 if k == toxicity.unit_key("bad") else -1.0 for k in keys.tolist()], dtype=np.float32)
    model = toxicity.Model(keys, unit, np.zeros(0, np.uint64), np.zeros(0, np.float32), np.zeros(3))
    texts = [f"bad w{i} good w{i + 1} w{i}" for i in range(50)] + ["bad", "good good"]
    whole = [toxicity.Reader(model).evidence(t) for t in texts]
    monkeypatch.setattr(toxicity, "CACHE", 3)
    reader = toxicity.Reader(model)
    assert [reader.evidence(t) for t in texts] == whole


# vectors
def test_permutation_index_finds_most_neighbours(spark, sf_dir):
    rows = vectors.op6_permutation_index(spark, sf_dir).collect()
    t = spark.read.parquet(f"{sf_dir}/embeddings.parquet").toPandas()
    x, ids = np.stack(t.embedding).astype(float), t.vec_id.to_numpy()
    by = {}
    for r in sorted(rows, key=lambda r: (r.query_id, r.rank)):
        by.setdefault(r.query_id, []).append(r)
    hit = []
    for q in ids[ids % 20 == 0]:
        s = x @ x[ids == q][0]
        s[ids == q] = -9
        want = ids[np.lexsort((ids, -s))[:20]]
        got = by[q]
        assert [r.rank for r in got] == list(range(1, 21)) and all(abs(r.score - s[ids == r.vec_id][0]) < 1e-12 for r in got)
        hit.append(len({r.vec_id for r in got} & set(want)) / 20)
    assert np.mean(hit) >= 0.9


def test_vectors_that_take_no_part(spark):
    bad = [(1, None), (2, [0.0, 0.0]), (3, [float("nan"), 1.0]), (4, [None, 1.0]), (5, [float("inf"), 0.0]), (6, [1.0])]
    fine = [(i, [float(i), 1.0]) for i in range(20, 26)] + [(20, [7.0, 1.0])]
    table = vectors.usable(spark.createDataFrame(bad + fine, "vec_id long, embedding array<float>"))
    got = vectors.nearest(table, table.where("vec_id % 20 = 0"), 20).collect()
    # two rows of id 20 with other vectors: each is asked and is a candidate of the other
    ranks = Counter((r.rank, r.vec_id) for r in got)
    assert {r.query_id for r in got} == {20} and len(got) == 12 and Counter(r.rank for r in got) == Counter({i: 2 for i in range(1, 7)}) and max(ranks.values()) <= 2
    twice = vectors.nearest(table.union(table), table.union(table).where("vec_id = 20 and x[0] = 20"), 20).collect()
    assert sorted(r.rank for r in twice) == list(range(1, 13)) and max(Counter(r.vec_id for r in twice).values()) == 2


# shards
def test_a_dead_writers_claim_and_files_are_cleared(spark, odd, tmp_path):
    store = sharding.ShardStore(spark, str(tmp_path), claim_seconds=0, orphan_seconds=0)
    store.append(odd.coalesce(1))
    (tmp_path / "manifests" / ".000000000002.claim").touch()
    odd.coalesce(1).write.parquet(str(tmp_path / "data" / "left"))
    assert store.append(odd.coalesce(1)) == 2 and store.read(odd.schema).count() == 2 * len(ODD)
    assert store.vacuum() == 1 and store.read(odd.schema).count() == 2 * len(ODD)
    with pytest.raises(ValueError):
        store.vacuum(0)
    with pytest.raises(sharding.Conflict):
        store.commit(1, [])
    named = odd.withColumn("_arrival", F.lit("own"))
    other = sharding.ShardStore(spark, str(tmp_path / "other"))
    other.append_each(named, F.col("doc_id") % 2)
    assert {r["_arrival"] for r in other.read(named.schema).collect()} == {"own"} and other.read(named.schema).count() == len(ODD)


def test_shards_keep_every_row_through_compaction(spark, odd, tmp_path):
    store = sharding.ShardStore(spark, str(tmp_path), target_bytes=1 << 20, fan_in=3)
    assert store.read(odd.schema).count() == 0
    for _ in range(3):
        store.append(odd.coalesce(1))
    assert store.compact() == 4 and [r.level for r in store.manifest()[1]] == [1]
    rest = store.append(odd.coalesce(1))
    version, runs = store.manifest()
    assert version == rest == store.compact() and [r.level for r in runs] == [1, 0]
    rows = Counter(tuple(r) for r in store.read(odd.schema).collect())
    assert rows == Counter({tuple(r): 4 for r in odd.distinct().collect()})
    assert store.read(odd.schema, version=2).count() == 2 * len(ODD)
    assert store.vacuum() > 0 and store.versions() == [version] and store.read(odd.schema).count() == 4 * len(ODD)


def test_two_writers_of_one_version_conflict(spark, odd, tmp_path):
    store = sharding.ShardStore(spark, str(tmp_path))
    store.append(odd)
    with pytest.raises(sharding.Conflict):
        store.commit(0, [])
    assert store.manifest()[0] == 1


def test_sharding_query_returns_every_document(spark, sf_dir):
    rows = sharding.op2_size_tiered(spark, sf_dir).collect()
    docs = {r.doc_id: r.text for r in documents(spark, sf_dir).collect()}
    assert len(rows) == len(docs) and all(r.text_md5 == hashlib.md5(docs[r.doc_id].encode()).hexdigest() and r.level is not None for r in rows)
