import hashlib
import random
import re

from pyspark.sql import functions as F

from biclique_spark.llm import exact_dedup, ngram_join, substring, words
from tests.llm.helpers import WORD, docs, random_texts

ODD = [None, "", "  ", "a b", "a\tb", "a  b", "a b", "A b", "x" * 50_000, "x" * 50_000, "é è", None, " a b"]


def brute_exact(rows):
    groups = {}
    clean = {i: re.sub(r"[\x20\x09-\x0D]+", " ", t or "") for i, t in rows}
    for i, t in clean.items():
        groups.setdefault(t, []).append(i)
    return {(i, min(groups[t]), len(groups[t]), i == min(groups[t]), hashlib.sha256(t.encode()).hexdigest()) for i, t in clean.items()}


def test_exact_dedup(spark):
    texts = ODD + ["hot"] * 40
    got = exact_dedup.dedup(docs(spark, texts))
    assert {tuple(r) for r in got.collect()} == brute_exact(enumerate(texts))


def test_exact_dedup_in_batches_and_by_weak_digest(spark):
    texts = ODD + random_texts(random.Random(1), 60)
    d = docs(spark, texts).repartition(4)
    want = brute_exact(enumerate(texts))
    got = exact_dedup.dedup(d, files_per_trigger=1)
    assert {tuple(r) for r in got.collect()} == want
    weak = exact_dedup.dedup(d, digest=lambda t: (F.length(t) % 3).cast("string"))
    assert {tuple(r) for r in weak.collect()} == want


def test_exact_dedup_edges(spark):
    empty = exact_dedup.dedup(docs(spark, ["a"]).limit(0))
    assert empty.columns == ["doc_id", "keep_id", "group_size", "kept", "text_sha256"] and not empty.collect()
    got = exact_dedup.dedup(docs(spark, ["a", "a", "b"], ids=[None, 3, None])).collect()
    assert sorted((r.doc_id is None, r.keep_id, r.group_size, r.kept) for r in got if r.keep_id == 3) == [(False, 3, 2, True), (True, 3, 2, False)]
    twice = exact_dedup.dedup(docs(spark, ["a", "a"], ids=[5, 5])).collect()
    assert [r.kept for r in twice] == [True, True] and twice[0].group_size == 2
    kept = exact_dedup.keep_first(docs(spark, ["a", "a", "b"]))
    assert {r.doc_id for r in kept.collect()} == {0, 2} and len(kept.columns) == 9


def brute_windows(rows, n):
    words = {i: WORD.findall(t or "") for i, t in rows}
    first = {}
    for i in sorted(words):
        for k in range(len(words[i]) - n + 1):
            first.setdefault(tuple(words[i][k : k + n]), i)
    out = set()
    for i, w in words.items():
        gone = {k + j for k in range(len(w) - n + 1) if first[tuple(w[k : k + n])] < i for j in range(n)}
        kept = " ".join(x for k, x in enumerate(w) if k not in gone)
        out.add((i, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return out


def test_substring_against_brute_force(spark):
    rng = random.Random(2)
    passage = " ".join(f"p{k}" for k in range(30))
    texts = ODD + random_texts(rng, 60, vocabulary=8) + [f"start{k} {passage} end{k}" for k in range(30)] + ["z " * 40]
    got = substring.remove_repeats(docs(spark, texts), 5)
    assert {tuple(r) for r in got.collect()} == brute_windows(enumerate(texts), 5)


def test_substring_edges(spark):
    assert not substring.remove_repeats(docs(spark, ["a"]).limit(0)).collect()
    t = " ".join(str(k) for k in range(20))
    rows = substring.remove_repeats(docs(spark, [t, t, t], ids=[4, 4, None]), with_text=True).collect()
    assert [(r.n_words, r.n_removed, r.kept) for r in rows] == [(20, 0, t)] * 3
    assert substring.sketch_bits(0) == 16 and substring.sketch_bits(1 << 60) == 30


def brute_components(rows, n, percent):
    sets = {}
    for i, t in rows:
        w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[i] = {tuple(w[k : k + n]) for k in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set())
    comp = {i: i for i in sets}

    def find(x):
        while comp[x] != x:
            x = comp[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                shared = len(sets[a] & sets[b])
                if 100 * shared >= percent * (len(sets[a]) + len(sets[b]) - shared):
                    x, y = sorted((find(a), find(b)))
                    comp[y] = x
    return {(i, len(sets[i]), find(i)) for i in ids}


def near_copies(rng, base, n):
    out = []
    for _ in range(n):
        w = base.split()
        for _ in range(rng.randrange(0, 5)):
            w[rng.randrange(len(w))] = f"new{rng.randrange(10_000)}"
        out.append(" ".join(w))
    return out


def test_ngram_join_against_brute_force(spark):
    rng = random.Random(3)
    base = " ".join(f"b{rng.randrange(500)}" for _ in range(150))
    passage = " ".join(f"p{k}" for k in range(40))
    texts = ODD + random_texts(rng, 60, words=60) + near_copies(rng, base, 60) + [f"{passage} " + " ".join(f"q{k}x{j}" for j in range(30 + k)) for k in range(30)]
    texts += [passage.upper(), passage + " more", passage]
    for n, percent in ((4, 85), (5, 80), (2, 60)):
        got = ngram_join.join_components(docs(spark, texts), n, percent)
        assert {tuple(r) for r in got.collect()} == brute_components(list(enumerate(texts)), n, percent), (n, percent)


def test_ngram_join_edges(spark):
    assert not ngram_join.join_components(docs(spark, ["a"]).limit(0)).collect()
    got = ngram_join.join_components(docs(spark, ["a b c", "a b c", "a b c", ""], ids=[4, 4, None, None])).collect()
    assert sorted((r.doc_id or -1, r.n_shingles, r.component_id) for r in got if r.doc_id) == [(4, 1, 4), (4, 1, 4)]
    assert all(r.component_id is None for r in got if r.doc_id is None)


def test_components_of_a_chain(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101)], "a long, b long")
    got = {r.doc_id: r.comp for r in ngram_join.components(links).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100}


def test_words_that_a_polynomial_would_confuse(spark):
    """Two words whose letters are a bit parity sequence and its complement, and texts made of them."""
    bits = [bin(i).count("1") & 1 for i in range(1024)]
    one, other = "".join("ab"[b] for b in bits), "".join("ba"[b] for b in bits)
    key = words.new_key()
    assert (words.word_codes(one.encode(), key) != words.word_codes(other.encode(), key)).all()
    texts = [f"{one} " * 20, f"{other} " * 20]
    assert all(r.n_removed == 0 for r in substring.remove_repeats(docs(spark, texts)).collect())
    assert [r.component_id for r in ngram_join.join_components(docs(spark, texts)).orderBy("doc_id").collect()] == [0, 1]


def test_word_codes_tell_words_apart():
    rng = random.Random(4)
    text = " ".join("".join(rng.choice("ab\x00é") for _ in range(rng.randrange(1, 45))) for _ in range(3000)) + "\ta\x0b\x0c b\r\n"
    raw, key = text.encode(), words.new_key()
    split, codes = raw.split(), words.word_codes(raw, key)
    assert len(split) == len(codes) and len({(w, tuple(c)) for w, c in zip(split, codes.tolist())}) == len(set(split)) == len(set(codes[:, 0].tolist()))
    assert not len(words.word_codes(b"", key)) and not len(words.word_codes(b" \t", key))


REPEATED = [(None, "a"), (3, "a"), (5, "c"), (5, "b"), (4, "b"), (None, "z"), (None, "z"), (6, "d e"), (6, "d  e")]


def test_keep_first_judges_rows(spark):
    d = docs(spark, [t for _, t in REPEATED], ids=[i for i, _ in REPEATED])
    kept = sorted(((r.doc_id is None, r.doc_id), " ".join((r.text or "").split())) for r in exact_dedup.keep_first(d).collect())
    assert kept == [((False, 3), "a"), ((False, 4), "b"), ((False, 5), "c"), ((False, 6), "d e"), ((True, None), "z")]


def test_keep_one_judges_rows(spark):
    d = docs(spark, [t for _, t in REPEATED] + [None, ""], ids=[i for i, _ in REPEATED] + [7, None])
    kept = sorted((r.doc_id is None, r.doc_id or 0, " ".join((r.text or "").split())) for r in ngram_join.keep_one(d).collect())
    assert kept == [(False, 3, "a"), (False, 4, "b"), (False, 5, "c"), (False, 6, "d e"), (False, 7, ""), (True, 0, ""), (True, 0, "z")]
    plain = ngram_join.keep_one(docs(spark, ["a b", "a  b", "c"], ids=[3, 1, 2]))
    assert sorted(r.doc_id for r in plain.collect()) == [1, 2] and len(plain.columns) == 9
    assert not ngram_join.keep_one(d.limit(0)).collect()


def test_substring_dedup_shrinks_heaps_between_its_steps(spark, monkeypatch):
    """Before the sketch, before windows are sent and before texts are read again; results are as ever."""
    calls = []
    monkeypatch.setattr(substring, "shrink_heaps", calls.append)
    line = " ".join(f"w{i}" for i in range(13))
    docs = spark.createDataFrame([(1, f"a {line}"), (2, f"{line} b"), (3, None)], "doc_id long, text string")
    rows = {r.doc_id: (r.n_words, r.n_removed) for r in substring.remove_repeats(docs).collect()}
    assert rows == {1: (14, 0), 2: (14, 13), 3: (0, 0)} and len(calls) == 3
