"""Toxicity by Levenshtein automata on a lexicon trie, with context windows.

A lexicon of words and word beginnings is learned from a bounded sample of labelled rows. Its trie and the
Levenshtein automata of its entries are walked together, as one automaton that is made deterministic while it
is used, so a word costs a step a letter and misspelled entries are found too. Around each hit a window of
words tells abuse from quotation. A logistic model over what was found gives the score.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biclique_spark.llm.quality import remainder

#: Labelled rows used for fitting at most; entries of a lexicon at most; words on each side of a hit.
SAMPLE, ENTRIES, WINDOW = 8_000, 256, 8
#: Memory of words already walked, and of the automaton's states.
KEPT, STATES = 1 << 20, 1 << 16
_LETTERS = re.compile(r"[^\W_]+(?:['’-][^\W_]+)*")
_QUOTES = "\"“”„«»‹›"
#: Words of telling what someone else said, in the languages of the texts.
_REPORTING = frozenset(
    "said says quoted quote wrote called reported claimed according sagte sagt schrieb zitierte dit écrit cité selon dijo dice escribió citó según".split()
)
#: The automaton of the last lexicon and the words it has walked; tasks of one Python worker share them.
_walked: dict[tuple, tuple[LexiconAutomaton, dict]] = {}
FEATURES = ("exact", "fuzzy", "entries", "share", "quoted", "reported", "bare")


def edits_allowed(entry: str, prefix: bool) -> int:
    """Short words have too many neighbours; a beginning says less than a word."""
    return 0 if prefix or len(entry) < 4 else 1 if len(entry) < 9 else 2


class LexiconAutomaton:
    """match(word): (entry number, edits) of the entry with the fewest edits, the first of equals; None without one.

    With ``swaps`` two neighbouring letters exchanged are one edit, else two. Entries in ``strict`` allow none.
    """

    def __init__(self, entries: Iterable[tuple[str, bool]], swaps: bool = False, strict: frozenset = frozenset()):
        self.entries, self.swaps = list(entries), swaps
        self.child: list[dict[str, int]] = [{}]
        self.ends: list[list[int]] = [[]]
        self.room = [0]  # edits that some entry below still allows
        self.limit = [0 if e in strict else edits_allowed(*e) for e in self.entries]
        for k, (word, _) in enumerate(self.entries):
            node = 0
            self.room[0] = max(self.room[0], self.limit[k])
            for c in word:
                if c not in self.child[node]:
                    self.child[node][c] = len(self.child)
                    self.child.append({})
                    self.ends.append([])
                    self.room.append(0)
                node = self.child[node][c]
                self.room[node] = max(self.room[node], self.limit[k])
            self.ends[node].append(k)
        self.letters = {c for d in self.child for c in d}
        self._reset()

    def _reset(self) -> None:
        self.names: dict[tuple, int] = {}
        self.states: list[tuple] = []
        self.steps: list[dict[str, int]] = []
        self.start = self._state({(0, 0, "")}, None)

    def _state(self, positions: set[tuple[int, int, str]], won: tuple[int, int] | None) -> int:
        """positions: (node, edits, letter due to complete a swap, or none); won: the best beginning matched so far."""
        best: dict[tuple[int, str], int] = {}
        todo = list(positions)
        while todo:
            node, e, due = todo.pop()
            if e > self.room[node] or best.get((node, due), 99) <= e:
                continue
            best[node, due] = e
            if not due:
                todo += [(x, e + 1, "") for x in self.child[node].values()]  # a letter of the entry left out
        for (node, due), e in best.items():
            for k in self.ends[node]:
                if not due and self.entries[k][1] and e <= self.limit[k]:
                    won = min(won or (e, k), (e, k))
        name = (tuple(sorted((node, e, due) for (node, due), e in best.items())), won)
        if name not in self.names:
            self.names[name] = len(self.states)
            self.states.append(name)
            self.steps.append({})
        return self.names[name]

    def _step(self, state: int, c: str) -> int:
        positions, won = self.states[state]
        after = set()
        for node, e, due in positions:
            if due:
                if c == due:
                    after.add((node, e, ""))
                continue
            after.add((node, e + 1, ""))  # a letter too many
            for x, to in self.child[node].items():
                after.add((to, e + (x != c), ""))
                if self.swaps and x != c and c in self.child[to]:
                    after.add((self.child[to][c], e + 1, x))
        out = self.steps[state][c] = self._state(after, won)
        return out

    def match(self, word: str) -> tuple[int, int] | None:
        if len(self.states) > STATES:
            self._reset()
        at = self.start
        for c in word:
            c = c if c in self.letters else "\0"
            to = self.steps[at].get(c)
            at = self._step(at, c) if to is None else to
        positions, won = self.states[at]
        found = [(e, k) for node, e, due in positions if not due for k in self.ends[node] if e <= self.limit[k]]
        best = min(found + ([won] if won else []), default=None)
        return (best[1], best[0]) if best else None


@dataclass
class ToxicityModel:
    entries: list[tuple[str, bool]]
    weights: np.ndarray = field(default_factory=lambda: np.zeros(len(FEATURES)))
    bias: float = 0.0
    strict: frozenset = frozenset()

    def __getstate__(self):
        return self.entries, self.weights, self.bias, self.strict

    def __setstate__(self, state):
        self.entries, self.weights, self.bias, self.strict = state
        self._ready()

    def __post_init__(self):
        self._ready()

    def _ready(self) -> None:
        key = tuple(self.entries), self.strict
        if key not in _walked:
            _walked.clear()
            _walked[key] = LexiconAutomaton(self.entries, True, self.strict), {}
        self.automaton, self.known = _walked[key]

    def _hit(self, token: str) -> tuple[int, int] | None:
        """The best match among a token's words."""
        found = [m for w in _LETTERS.findall(token) if (m := self.automaton.match(w))]
        return min(found, key=lambda m: (m[1], m[0]), default=None)

    def features(self, text: str) -> np.ndarray:
        tokens = text.lower().split()
        if len(self.known) > KEPT:
            self.known.clear()
        known = self.known
        for w in [w for w in set(tokens) if w not in known]:
            known[w] = self._hit(w)
        hits = [(i, h) for i, h in enumerate(map(known.__getitem__, tokens)) if h]
        if not hits:
            return np.zeros(len(FEATURES))
        quoted = [self._quoted(tokens, i) for i, _ in hits]
        told = [any(w.strip(",.:;") in _REPORTING for w in tokens[max(0, i - WINDOW) : i + WINDOW + 1]) for i, _ in hits]
        exact = sum(h[1] == 0 for _, h in hits)
        bare = sum(not q and not r for q, r in zip(quoted, told, strict=True))
        return np.array([
            math.log1p(exact), math.log1p(len(hits) - exact), math.log1p(len({h[0] for _, h in hits})),
            math.sqrt(len(hits) / len(tokens)), sum(quoted) / len(hits), sum(told) / len(hits), float(bare > 0),
        ])

    @staticmethod
    def _quoted(tokens: list[str], i: int) -> bool:
        """A quotation mark opens before the hit and one closes behind it, both within the window."""
        before = sum(c in _QUOTES for w in tokens[max(0, i - WINDOW) : i] for c in w) + (tokens[i][:1] in _QUOTES)
        behind = sum(c in _QUOTES for w in tokens[i + 1 : i + WINDOW + 1] for c in w) + (tokens[i][-1:] in _QUOTES)
        return before % 2 == 1 and behind > 0

    def score(self, text: str) -> float:
        z = float(self.features(text) @ self.weights) + self.bias
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def learn_lexicon(rows: list[tuple[list[str], int]], gain: int = 3, purity: float = 0.95, kin: int = 8) -> list[tuple[str, bool]]:
    """Words and beginnings that mark toxic rows: the one that covers most uncovered toxic rows is taken again and
    again, if at least ``purity`` of the rows with it (rates, so that classes weigh the same) are toxic; of equal
    ones a whole word goes before a beginning, the longer before the shorter."""
    toxic = [set(ws) for ws, y in rows if y]
    clean = [set(ws) for ws, y in rows if not y]
    if not toxic or not clean:
        return []

    def terms(w: str) -> list[tuple[str, bool]]:
        return [(w, False)] + [(w[:n], True) for n in range(4, min(9, len(w)))]

    in_toxic: dict[tuple[str, bool], set[int]] = {}
    family: dict[tuple[str, bool], set[str]] = {}
    for i, ws in enumerate(toxic):
        for w in ws:
            for t in terms(w):
                in_toxic.setdefault(t, set()).add(i)
                family.setdefault(t, set()).add(w)
    # A beginning is one only for many words, and the longest of those that the same rows have.
    in_toxic = {t: s for t, s in in_toxic.items() if len(s) >= gain and (not t[1] or len(family[t]) >= kin)}
    longer = {(t[0][:-1], True): t for t in in_toxic if t[1]}
    in_toxic = {t: s for t, s in in_toxic.items() if not t[1] or t not in longer or in_toxic[longer[t]] != s}
    in_clean: Counter = Counter()
    for ws in clean:
        in_clean.update({t for w in ws for t in terms(w) if t in in_toxic})
    base = len(clean) / len(toxic)
    pure = {t: s for t, s in in_toxic.items() if len(s) * base >= purity * (len(s) * base + in_clean[t] * max(1.0, base)) and in_clean[t] <= (0 if t[1] else 0.05) * len(s)}
    left, out = set(range(len(toxic))), []
    while left and len(out) < ENTRIES:
        best = max(pure, key=lambda t: (len(pure[t] & left), not t[1], len(t[0]), t[0]), default=None)
        if best is None or len(pure[best] & left) < gain:
            break
        out.append(best)
        left -= pure.pop(best)
    # Other pure terms that mark many toxic rows are entries too, though rows with them are covered.
    for t in sorted(pure, key=lambda t: (-len(pure[t]), t)):
        if len(out) >= ENTRIES or len(pure[t]) < max(4 * gain, 0.02 * len(toxic)):
            break
        # A whole word under a beginning is one as well: it allows edits, the beginning none.
        if not t[1] or not any(p and t[0].startswith(e) for e, p in out):
            out.append(t)
    return out


def near_clean(entries: list[tuple[str, bool]], rows: list[tuple[list[str], int]]) -> frozenset:
    """Words of four letters that are one edit from a word of a clean row: these allow none."""
    short = [e for e in entries if not e[1] and len(e[0]) == 4]
    clean = {w for ws, y in rows if not y for w in ws if 3 <= len(w) <= 5} if short else set()
    automata = {e: LexiconAutomaton([e], True) for e in short}
    return frozenset(e for e, a in automata.items() if any((m := a.match(w)) and m[1] for w in clean))


def fit_logistic(x: np.ndarray, y: np.ndarray, steps: int = 400, decay: float = 1e-3) -> tuple[np.ndarray, float]:
    """Gradient descent on scaled columns, from zero; the same rows give the same model."""
    scale = np.maximum(np.abs(x).max(0), 1e-9)
    a = np.hstack([x / scale, np.ones((len(x), 1))])
    w, g = np.zeros(a.shape[1]), np.full(a.shape[1], 1e-9)
    for _ in range(steps):
        d = a.T @ (1 / (1 + np.exp(-np.clip(a @ w, -30, 30))) - y) / len(y) + decay * np.append(w[:-1], 0) / 10
        g += d * d
        w -= 0.5 * d / np.sqrt(g)
    return w[:-1] / scale, float(w[-1])


def _prepared(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))


def fit(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, label_col: str) -> ToxicityModel:
    """From at most SAMPLE rows of labels, those with the smallest digests of their ids."""
    rows = labels.where(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.col(label_col).cast("int").alias("y"))
    rows = rows.orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id", "y").limit(SAMPLE)
    some = _prepared(docs, id_col, text_col).join(F.broadcast(rows), "doc_id").select("doc_id", "text", "y")

    def words(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in source:
            found = [sorted(set(_LETTERS.findall(t.lower()))) for t in b.column(1).to_pylist()]
            yield pa.record_batch([b.column(0), b.column(2), pa.array(found, pa.list_(pa.string()))], ["doc_id", "y", "words"])

    t = some.mapInArrow(words, "doc_id long, y int, words array<string>").toArrow().sort_by("doc_id")
    learned = list(zip(t["words"].to_pylist(), t["y"].to_pylist(), strict=True))
    entries = learn_lexicon(learned)
    model = ToxicityModel(entries, strict=near_clean(entries, learned))
    if not model.entries:
        share = float(np.mean(t["y"].to_numpy())) if t.num_rows else 0.0
        model.bias = math.log((share + 1e-6) / (1 - share + 1e-6))
        return model

    def found(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in source:
            x = [model.features(t).tolist() for t in b.column(1).to_pylist()]
            yield pa.record_batch([b.column(0), b.column(2), pa.array(x, pa.list_(pa.float64()))], ["doc_id", "y", "x"])

    t = some.mapInArrow(found, "doc_id long, y int, x array<double>").toArrow().sort_by("doc_id")
    x, y = np.array(t["x"].to_pylist()), t["y"].to_numpy()
    # Misspelled terms are rare in labelled rows: each toxic row with hits counts once more as if all were misspelled.
    again = x[(y == 1) & (x[:, 0] > 0)].copy()
    again[:, 1], again[:, 0] = again[:, 0], 0
    model.weights, model.bias = fit_logistic(np.vstack([x, again]), np.concatenate([y, np.ones(len(again))]))
    return model


def toxicity(
    docs: DataFrame,
    labels: DataFrame,
    folds: int = 4,
    held: int = 2,
    threshold: float = 0.3,
    id_col: str = "doc_id",
    text_col: str = "text",
    label_col: str = "toxic",
) -> DataFrame:
    """doc_id, held_out, score, predicted for each row of docs.

    Labels are learned only from ids whose crc32 modulo ``folds`` is not ``held``. Null and empty texts have no
    hits and get the score of a text without any; null labels are not used; rows with a null id are scored and
    not held out; repeated rows get the same score; of equal matches the first entry counts. An empty table
    gives an empty result; only the text enters a score, and no column but those named is read.
    """
    model = fit(docs, labels.where(remainder(F.col(id_col), folds) != held), id_col, text_col, label_col)

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in source:
            yield pa.record_batch([b.column(0), pa.array([model.score(t) for t in b.column(1).to_pylist()], pa.float64())], ["doc_id", "score"])

    scored = _prepared(docs, id_col, text_col).mapInArrow(run, "doc_id long, score double")
    return scored.select(
        "doc_id",
        F.coalesce(remainder(F.col("doc_id"), folds) == held, F.lit(False)).alias("held_out"),
        "score",
        (F.col("score") >= threshold).cast("int").alias("predicted"),
    )
