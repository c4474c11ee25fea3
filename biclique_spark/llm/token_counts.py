"""Token counts of whole texts, as a library's tokenizer gives them.

Arrow batches go in and only lengths come out. Texts are cut where the tokenizer's own pre-tokens always
end, so that pieces may be counted apart: before a space that follows a non-space, and before the last space
of a run. Pieces that were counted before are looked up; the others go to the library in batches balanced
by their bytes.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biclique_spark.llm.common import lean, parts

#: A space inside a run of white space, or white space at the end: these cuts are not safe.
_INSIDE = re.compile(r"\s (?:\s|\Z)")
#: Bytes of text handed to the library at once; bytes of pieces whose counts are kept, and what an entry takes beside its text.
BATCH_BYTES, KEPT, ENTRY = 1 << 20, 160 << 20, 150

_counters: dict[str, BytePieces | WholeTexts] = {}


def pieces(text: str) -> list[str]:
    """Parts of a text whose byte-level pre-tokens are the text's own, in order; whole where white space is odd.

    Cuts are made before spaces only, so no special token's string is cut; counter() sees to it that none holds a space.
    """
    if _INSIDE.search(text):
        out, start = [], 0
        for m in re.finditer(r"(?<=\S) (?=\S)", text):
            out.append(text[start : m.start()])
            start = m.start()
        out.append(text[start:])
        return out
    head, *rest = text.split(" ")
    return ([head] if head else []) + [" " + x for x in rest]


def batches(texts: list[str], most: int = BATCH_BYTES, sizes: list[int] | None = None) -> Iterator[list[str]]:
    """Lists of no more bytes than ``most``; a text over the bound is a list of its own. sizes: bytes of the texts, where known."""
    batch, size = [], 0
    for t, n in zip(texts, sizes or [len(t) if t.isascii() else len(t.encode("utf-8", "surrogatepass")) for t in texts], strict=True):
        if batch and size + n > most:
            yield batch
            batch, size = [], 0
        batch.append(t)
        size += n
    if batch:
        yield batch


class BytePieces:
    """Counts by a byte-level tokenizer without normaliser, from counts of pieces."""

    def __init__(self, tokenizer):
        self.tokenizer, self.known, self.bytes = tokenizer, {"": 0}, 0

    def __call__(self, texts: list[str]) -> list[int]:
        cut = [pieces(t) for t in texts]
        if self.bytes > KEPT:
            self.known, self.bytes = {"": 0}, 0
        known = self.known
        new = list({p for parts in cut for p in parts if p not in known})
        for batch in batches(new):
            for p, e in zip(batch, self.tokenizer.encode_batch_fast(batch, add_special_tokens=False), strict=True):
                known[p] = len(e)
            self.bytes += ENTRY * len(batch) + sum(map(len, batch))
        return [sum(map(known.__getitem__, parts)) for parts in cut]


class WholeTexts:
    """Counts by any tokenizer, on whole texts: where no cut is known to be safe."""

    def __init__(self, count):
        self.count = count

    def __call__(self, texts: list[str]) -> list[int]:
        return [n for batch in batches(texts) for n in self.count(batch)]


def counter(path: str):
    """The counter for a tokenizer file; one is kept for each Python worker."""
    if path not in _counters:
        if path.endswith(".model"):
            import sentencepiece

            model = sentencepiece.SentencePieceProcessor(model_file=path)
            _counters[path] = WholeTexts(lambda texts: [len(x) for x in model.encode(texts, num_threads=1)])
        else:
            os.environ["TOKENIZERS_PARALLELISM"] = "false"
            from tokenizers import Tokenizer

            t = Tokenizer.from_file(path)
            t.no_truncation()
            t.no_padding()
            kind = type(t.pre_tokenizer).__name__
            spaced = any(" " in x.content for x in t.get_added_tokens_decoder().values())
            if kind == "ByteLevel" and not spaced and t.normalizer is None and "add_prefix_space=False" in repr(t.pre_tokenizer):
                _counters[path] = BytePieces(t)
            else:
                _counters[path] = WholeTexts(lambda texts: [len(e) for e in t.encode_batch(texts, add_special_tokens=False)])
    return _counters[path]


def token_counts(docs: DataFrame, path: str, limit: int = 512, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for each row.

    Null and empty texts have 0 tokens; null ids stay null; repeated rows are counted each; no row is
    compared with another, so ties cannot occur. Very long texts are cut at safe boundaries only. An empty
    table gives an empty result; other columns are not read. Nothing is shuffled.
    """

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(path)
        for b in source:
            n: list[int] = []
            for some in parts(b, 1024):
                for part in batches(some.column(1).to_pylist(), sizes=some.column(2).to_pylist()):
                    n += count(part)
            yield pa.record_batch([b.column(0), b.column(2), pa.array(n, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), F.octet_length(text).cast("long").alias("n_bytes"))
    out = rows.mapInArrow(lean(run), "doc_id long, n_bytes long, n_tokens long")
    return out.withColumn("over_limit", F.col("n_tokens") > F.lit(limit))
