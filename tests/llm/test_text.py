import base64
import hashlib
import random
import struct

import public_tokenizers
import pytest
import tiktoken
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from biclique_spark.llm import bpe, chat, quality, token_counts, toxicity
from tests.llm.helpers import docs

RANKS, JSON = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.path("byte_bpe_50k.json")
ODD = [
    None, "", " ", "  ", "a  b", "a   b", "a ", "\n \n b", "x\n\n  y", "don't  we'll", "<|endoftext|> a<|endoftext|>", "日本 語  漢字",
    "a" * 3000, "😀 😀", "\x1c \x1c a", "a \t b", "zero​width", "word " * 3000,
]


def odd_texts():
    rng = random.Random(4)
    return ODD + ["".join(rng.choice("ab  \n\t é1!'s") for _ in range(rng.randint(1, 40))) for _ in range(400)]


def test_token_counts(spark):
    texts = odd_texts()
    t = Tokenizer.from_file(JSON)
    want = {(i, len((x or "").encode()), len(t.encode(x or "", add_special_tokens=False))) for i, x in enumerate(texts)}
    got = token_counts.token_counts(docs(spark, texts), JSON, 5).collect()
    assert {(r.doc_id, r.n_bytes, r.n_tokens) for r in got} == want
    assert all(r.over_limit == (r.n_tokens > 5) for r in got)


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "piece_bpe_32k.model"])
def test_token_counts_of_other_libraries(spark, name):
    path = public_tokenizers.path(name)
    got = {r.doc_id: r.n_tokens for r in token_counts.token_counts(docs(spark, ODD), path).collect()}
    if name.endswith(".model"):
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        want = {i: len(m.encode(x or "")) for i, x in enumerate(ODD)}
    else:
        t = Tokenizer.from_file(path)
        want = {i: len(t.encode(x or "", add_special_tokens=False)) for i, x in enumerate(ODD)}
    assert got == want
    assert not token_counts.token_counts(docs(spark, ["a"]).limit(0), path).collect()


def test_bpe_round_trip(spark):
    texts = odd_texts()
    with open(RANKS, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    own = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = {r.doc_id: r for r in bpe.round_trip(docs(spark, texts), RANKS, public_tokenizers.PATTERN).collect()}
    for i, x in enumerate(texts):
        ids = own.encode_ordinary(x or "")
        assert got[i].n_tokens == len(ids)
        assert got[i].ids_sha256 == hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256((x or "").encode()).hexdigest()
    encoded = bpe.encode(docs(spark, texts), RANKS, public_tokenizers.PATTERN)
    back = {r.doc_id: r.text for r in bpe.decode(encoded, RANKS, public_tokenizers.PATTERN).collect()}
    assert back == {i: x or "" for i, x in enumerate(texts)}
    assert not bpe.round_trip(docs(spark, ["a"]).limit(0), RANKS, public_tokenizers.PATTERN).collect()


def test_minimal_perfect_hash():
    keys = [f"k{i}".encode() for i in range(5000)]
    h = bpe.MinimalPerfectHash(keys)
    assert sorted(map(h, keys)) == list(range(5000))
    assert 0 <= h(b"other") < 5000


TURNS = "conv_id long, turn long, role string, text string, ts string, segments string"


def test_chat_reads_back(spark):
    said = ["\\### Assistant: </turn> ok", "<turn>x<body>", None, "", "a\n</turn>\n<part>", "\\<\\part>", "<", "</", "é\\", "</turn", "turn>"]
    rng = random.Random(5)
    rows = [(c, t, rng.choice(["user", "assistant", "system", None, "a<body>b"]), rng.choice(said), "x", "y") for c in range(40) for t in range(rng.randrange(1, 9))]
    rows += [(50, 1, "user", "b", "", ""), (50, 1, "user", "a", "", ""), (50, None, "user", "c", "", ""), (None, 1, "assistant", "n", "", "")]
    df = spark.createDataFrame(rows, TURNS)
    made = chat.format_chats(df)
    assert all("".join(s.text for s in r.segments) == r.formatted for r in made.collect())
    got = {r.conv_id: r for r in chat.digests(made).collect()}
    whole = {}
    for c, t, role, text, *_ in rows:
        whole.setdefault(c, []).append(((t is not None, t or 0), role or "", text or ""))
    assert set(got) == set(whole)
    for c, turns in whole.items():
        turns.sort()
        flat = "".join(f"{r}\n{x}\n" for _, r, x in turns)
        loss = "".join(x for _, r, x in turns if r == "assistant")
        assert got[c].n_turns == len(turns)
        assert got[c].turns_sha256 == hashlib.sha256(flat.encode()).hexdigest()
        assert (got[c].loss_chars, got[c].loss_sha256) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    assert got[50].n_turns == 3
    assert not chat.digests(chat.format_chats(df.limit(0))).collect()
    plan = chat.digests(made)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_automaton_against_edit_distance():
    def distance(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            row, old = [i], row
            for j, y in enumerate(b, 1):
                row.append(min(row[-1] + 1, old[j] + 1, old[j - 1] + (x != y)))
        return row[-1]

    entries = [("idiot", False), ("worthless", False), ("scum", False), ("lowe", True), ("stupid", False), ("stup", True)]
    auto = toxicity.LexiconAutomaton(entries)
    rng = random.Random(6)
    for _ in range(3000):
        w = list(rng.choice(entries)[0])
        for _ in range(rng.randrange(4)):
            k = rng.randrange(len(w) + 1)
            w[k : k + rng.randrange(2)] = [rng.choice("idotwrhlescumx")] * rng.randrange(2)
        w = "".join(w)
        want = []
        for k, (e, prefix) in enumerate(entries):
            limit = toxicity.edits_allowed(e, prefix)
            d = min(distance(w[:n], e) for n in range(len(w) + 1)) if prefix else distance(w, e)
            if d <= limit:
                want.append((d, k))
        got = auto.match(w)
        assert (got and (got[1], got[0])) == (min(want) if want else None), w


def labelled(spark, n=400):
    rng = random.Random(7)
    plain = ["".join(rng.choice("aeioulmnrst") for _ in range(rng.randrange(2, 9))) for _ in range(300)]
    texts, quality_, toxic = [], [], []
    for i in range(n):
        w = [rng.choice(plain) for _ in range(rng.randrange(20, 80))]
        bad, junk = i % 7 == 0, i % 5 == 0
        if bad:
            for _ in range(3):
                w.insert(rng.randrange(len(w)), rng.choice(["dimwitted", "blockhead", "nincompoop"]))
        if junk:
            w = [x.upper() + "!!" for x in w]
        texts.append(" ".join(w))
        quality_.append(int(not junk))
        toxic.append(int(bad))
    labels = spark.createDataFrame([(i, quality_[i], toxic[i], "x") for i in range(n)] + [(None, 1, 0, "y"), (3, None, None, "z")], "doc_id long, quality int, toxic int, text string")
    return docs(spark, texts + [None, ""], ids=list(range(n)) + [None, n]), labels, quality_, toxic


def accuracy(rows, truth):
    held = [r for r in rows if r.held_out and r.doc_id is not None and r.doc_id < len(truth)]
    assert held
    return sum(r.predicted == truth[r.doc_id] for r in held) / len(held)


def test_quality_on_held_out_rows(spark):
    d, labels, truth, _ = labelled(spark)
    rows = quality.quality(d, labels).collect()
    assert len(rows) == len(truth) + 2 and all(0 <= r.score <= 1 for r in rows)
    assert accuracy(rows, truth) > 0.95
    again = {r.doc_id: r.score for r in quality.quality(d.repartition(3), labels).collect()}
    assert all(abs(again[r.doc_id] - r.score) < 1e-4 for r in rows if r.doc_id is not None)
    kept = quality.keep(d, labels)
    assert kept.columns == d.columns and {r.doc_id for r in kept.collect()} == {r.doc_id for r in rows if r.predicted}
    assert not quality.quality(d.limit(0), labels).collect()
    assert {r.score for r in quality.quality(d, labels.limit(0)).collect()} <= {r.score for r in quality.quality(d, labels.limit(0)).collect()}


def test_pairs_in_linear_time():
    import numpy as np

    m = quality.FactorisationMachine(np.zeros((len(quality.STATS), quality.BINS - 1), np.float32))
    rng = np.random.default_rng(1)
    i, x = rng.integers(0, quality.WIDTH, 9), rng.normal(size=9).astype(np.float32)
    z, _ = m.sums(i, x, np.array([0, 4]))
    for s, (a, b) in enumerate(((0, 4), (4, 9))):
        slow = sum(float(m.v[i[j]] @ m.v[i[k]]) * x[j] * x[k] for j in range(a, b) for k in range(a, j)) + float(m.w[i[a:b]] @ x[a:b])
        assert abs(slow - z[s]) < 1e-4


def test_toxicity_on_held_out_rows(spark):
    d, labels, _, truth = labelled(spark)
    rows = toxicity.toxicity(d, labels).collect()
    assert len(rows) == len(truth) + 2 and accuracy(rows, truth) > 0.97
    assert not toxicity.toxicity(d.limit(0), labels).collect()
    model = toxicity.fit(d, labels, "doc_id", "text", "toxic")
    clean, quoted = "lorem blokhead nincompop dimwited", 'he said that "you are a nincompoop and a blockhead" to them'
    assert model.score(clean) > model.score("lorem ipsum")
    assert model.features(quoted)[4] > 0 and model.features(quoted)[6] == 0
    assert not {r.predicted for r in toxicity.toxicity(d, labels.limit(0)).collect()} - {0, 1}


def test_labels_of_held_out_rows_are_not_read(spark):
    d, labels, _, _ = labelled(spark)
    wrong = labels.withColumn("toxic", F.when(quality.remainder(F.col("doc_id"), 4) == 2, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a = {r.doc_id: r.score for r in toxicity.toxicity(d, labels).collect()}
    assert a == {r.doc_id: r.score for r in toxicity.toxicity(d, wrong).collect()}


def test_misspelled_short_terms_and_swaps(spark):
    auto = toxicity.LexiconAutomaton([("scum", False), ("moron", False), ("blockhead", False)], swaps=True)
    hits = {"scum": (0, 0), "skum": (0, 1), "csum": (0, 1), "scmu": (0, 1), "sc": None, "mroon": (1, 1), "mrono": None, "lbockhaed": (2, 2), "lbockhaedx": None}
    assert {w: auto.match(w) for w in hits} == hits
    rows = [(["scum", f"w{i}"], 1) for i in range(20)] + [(["word", f"w{i}"], 0) for i in range(20)]
    entries = toxicity.learn_lexicon(rows)
    assert ("scum", False) in entries and not toxicity.near_clean(entries, rows)
    assert ("scum", False) in toxicity.near_clean(entries, rows + [(["scam"], 0)])
    under = [([f"blockh{c}", "blockhead"], 1) for c in "abcdefghijklmnopqrst"] + rows
    entries = toxicity.learn_lexicon(under)
    assert ("blockhead", False) in entries
    d = docs(spark, ["you are scum lorem" if i % 2 else "you are fine lorem" for i in range(80)] + ["you are scmu lorem", "you are skum lorem", "you are fien lorem"])
    labels = spark.createDataFrame([(i, i % 2) for i in range(80)], "doc_id long, toxic int")
    assert [r.predicted for r in toxicity.toxicity(d, labels).orderBy("doc_id").collect()][80:] == [1, 1, 0]
    rows = [([f"blockh{c}"] + ["blockhead"] * (i % 2), 1) for i, c in enumerate("abcdefghijklmnopqrstuvwxyz" * 2)] + rows
    entries = toxicity.learn_lexicon(rows)
    assert any(p and "blockhead".startswith(e) for e, p in entries) and ("blockhead", False) in entries


def test_merges_replace_the_top_of_the_heap(monkeypatch):
    """Equal to merging the lowest pair, of equal ones the leftmost, until none is left; a pair that a merge makes takes the
    place of the pair it came from."""
    import heapq
    import random

    from biclique_spark.llm import bpe

    replaced, whole = [], heapq.heapreplace
    monkeypatch.setattr(heapq, "heapreplace", lambda heap, x: replaced.append(x) or whole(heap, x))
    rng = random.Random(5)
    for _ in range(40):
        tokens = [bytes([x]) for x in b"abc"]
        while len(tokens) < 30:
            if (t := rng.choice(tokens) + rng.choice(tokens)) not in tokens:
                tokens.append(t)
        ranks = {t: i for i, t in enumerate(tokens)}
        e = bpe.Encoder(ranks, r"\w+")
        for n in (1, 2, 3, 17, 60):
            raw = bytes(rng.choice(b"abc") for _ in range(n))
            parts = [raw[i : i + 1] for i in range(n)]
            while (best := min(((ranks[a + b], i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False)) if a + b in ranks), default=None)) is not None:
                parts[best[1] : best[1] + 2] = [parts[best[1]] + parts[best[1] + 1]]
            assert e.merged(raw) == [ranks[x] for x in parts]
    assert replaced


def test_bpe_tables_keep_half_a_million_words(monkeypatch):
    """Words of about 100 MB of entries are merged once, when the text comes again too; ids are decoded as they came."""
    e = bpe.Encoder({bytes([x]): 255 - x for x in range(256)}, public_tokenizers.PATTERN)
    merged, whole = [], e.merged
    monkeypatch.setattr(e, "merged", lambda raw: merged.append(1) or whole(raw))
    words = ["".join(chr(97 + (i >> 4 * k & 15)) for k in range(5)) for i in range(500_000)]
    texts = [" ".join(words[i : i + 5_000]) for i in range(0, len(words), 5_000)]
    once, first = [e.encode(t) for t in texts], len(merged)
    assert [e.encode(t) for t in texts] == once
    assert len(merged) == first
    assert [bytes(e.decode(x)).decode() for x in once] == texts
    assert e.decode(b"") == b""
