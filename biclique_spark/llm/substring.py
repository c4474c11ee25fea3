"""Substring deduplication with a count-min prefilter.

A window is ``window`` consecutive words. First every partition sketches its windows: a window falls into a cell,
and a cell counts the rows (documents) it had, as far as "more than one" goes. The sketches are cut into ranges of
cells and merged, a range a task, into one bit a cell: counted more than once. A count can only be too high, so no
repeated window is lost. A second pass sends on only the windows whose cell has its bit set, and groups them
exactly, by 96 bits of keyed hash from both halves of the words' numbers. A sketch of SPARSE cells a window leaves few others; beyond MOST_CELLS more windows
are grouped for nothing, and none is lost.

Both passes pack hashes into arrays of bytes, by range of cells, so that neither shuffle has a row a window. A chunk
of rows settles what it can by itself and sends one document's starts of each window to its range, so a window that a
third of all documents share costs its range one entry a chunk.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biclique_spark.llm.common import lean, shrink_heaps, size_of, written
from biclique_spark.llm.words import mixed, new_key, runs, word_codes

#: Cells for each window expected; the largest sketch (its bits are broadcast: 2^30 cells are 128 MB).
SPARSE, MOST_CELLS = 4, 1 << 30
#: Windows that a merging task gets about, and bytes of text gathered before hashes are sent on.
SHARE, GATHER = 1 << 20, 1 << 24


def sketch_bits(text_bytes: int) -> int:
    """Bits of a cell's number: SPARSE cells for each six bytes of text, a power of two, MOST_CELLS at most."""
    want = max(1 << 16, SPARSE * text_bytes // 6)
    return min((want - 1).bit_length(), MOST_CELLS.bit_length() - 1)


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).cast("binary").alias("text"))


def least_ids(h: np.ndarray, g: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order of rows by both hashes and, in that order, the smallest id of each row's window."""
    order = np.lexsort((g, h))
    first = np.ones(len(h), bool)
    first[1:] = (np.diff(h[order]) != 0) | (np.diff(g[order]) != 0)
    return order, np.minimum.reduceat(ids[order], np.nonzero(first)[0])[np.cumsum(first) - 1]


def _cells(hashes: np.ndarray, bits: int) -> np.ndarray:
    return hashes >> np.uint64(64 - bits)


def repeated_cells(docs: DataFrame, window: int, bits: int, ranges: int, key: bytes) -> DataFrame:
    """(range, bitmap): for each range of cells, a bit a cell that more than one row's windows fell into."""
    shift = bits - (ranges.bit_length() - 1)

    def sketch(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gathered, size = [], 0

        def sent() -> pa.RecordBatch:
            cells, counts = np.unique(np.concatenate(gathered), return_counts=True)
            cut = np.searchsorted(cells, np.arange(ranges + 1, dtype=np.uint64) << np.uint64(shift))
            part, once, more = [], [], []
            for r in range(ranges):
                own, n = cells[cut[r] : cut[r + 1]], counts[cut[r] : cut[r + 1]]
                if len(own):
                    part.append(r)
                    for to, c in ((once, own[n == 1]), (more, own[n > 1])):
                        # Differences of sorted cells are small numbers, which compress well.
                        to.append(np.diff((c - (np.uint64(r) << np.uint64(shift))).astype(np.uint32), prepend=np.uint32(0)).tobytes())
            return pa.record_batch([pa.array(part, pa.int32()), pa.array(once, pa.binary()), pa.array(more, pa.binary())], ["range", "once", "more"])

        for b in source:
            for text in b.column(0):
                raw = text.as_py()
                codes = word_codes(raw, key)
                if len(codes) >= window:
                    gathered.append(np.unique(_cells(runs(codes, window), bits)))
                    size += len(raw)
                if size > GATHER:
                    yield sent()
                    gathered, size = [], 0
        if gathered:
            yield sent()

    def merge(part: tuple, tables: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(1 << shift, np.uint8)
        for b in tables:
            for once, more in zip(b.column("once"), b.column("more"), strict=True):
                c = np.cumsum(np.frombuffer(once.as_buffer(), np.uint32), dtype=np.uint32)
                seen[c] = np.minimum(seen[c] + 1, 2)
                seen[np.cumsum(np.frombuffer(more.as_buffer(), np.uint32), dtype=np.uint32)] = 2
        bitmap = np.packbits(seen > 1).tobytes()
        yield pa.record_batch([pa.array([part[0].as_py()], pa.int32()), pa.array([bitmap], pa.binary())], ["range", "bitmap"])

    thin = docs.select("text").mapInArrow(lean(sketch), "range int, once binary, more binary")
    return thin.groupBy("range").applyInArrow(lean(merge), "range int, bitmap binary")


def repeats(docs: DataFrame, window: int, id_col: str, text_col: str) -> DataFrame:
    """(doc_id, runs): the words of each document that windows cover which also start in a row with a smaller id, as
    pairs of little-endian 32-bit numbers, from and up to. Ranges send what they find to buckets of documents, packed,
    and a bucket puts each document's windows together."""
    spark = docs.sparkSession
    shrink_heaps(spark)
    total, key = size_of(docs, text_col), new_key()
    rows = _rows(docs, id_col, text_col).where("doc_id is not null")
    bits = sketch_bits(total)
    # Ranges follow the data, so that the share of one stays the same.
    ranges = 1 << min(bits - 12, max(3, (total // 6 // SHARE).bit_length()))
    whole = np.zeros((ranges, (1 << bits) // ranges // 8), np.uint8)
    for part in written(repeated_cells(rows, window, bits, ranges, key), "substring-sketch").toLocalIterator():  # 1 / 8 byte a cell
        whole[part["range"]] = np.frombuffer(part["bitmap"], np.uint8)
    sketch = spark.sparkContext.broadcast(whole.ravel())
    del whole
    shrink_heaps(spark)
    shift = np.uint64(64 - (ranges.bit_length() - 1))

    def bucket_of(doc: np.ndarray) -> np.ndarray:
        return (mixed(doc.view(np.uint64)) % np.uint64(ranges)).astype(np.int64)

    def candidates(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Windows whose bit is set, packed by range: two hashes, the row they are of, and where they start."""
        bitmap, gathered, ids, size = sketch.value, [], [], 0

        def sent() -> pa.RecordBatch:
            h, g, doc, start = (np.concatenate(x) for x in zip(*gathered, strict=True))
            names = np.array(ids, np.int64)
            order, least = least_ids(h, g, names[doc])
            h, g, doc, start = h[order], g[order], doc[order], start[order]
            # A window that a smaller id of this chunk has is settled here; only the smallest id's starts are still open.
            settled = names[doc] > least
            to = np.where(settled, ranges + bucket_of(names[doc]), (h >> shift).astype(np.int64))
            by = np.argsort(to, kind="stable")
            cut = np.nonzero(np.diff(to[by], prepend=-1))[0]
            out: dict[str, list] = {k: [] for k in ("range", "h", "g", "doc", "low", "high", "ids")}
            for x, y in zip(cut, np.append(cut[1:], len(by)), strict=True):
                own, r = by[x:y], int(to[by[x]])
                used, back = np.unique(doc[own], return_inverse=True)
                hashes = (h[own], g[own]) if r < ranges else (h[:0], g[:0])
                values = (r, *hashes, back.astype(np.uint16), start[own].astype(np.uint16), (start[own] >> np.uint32(16)).astype(np.uint16), names[used])
                for k, v in zip(out, values, strict=True):
                    out[k].append(v if k == "range" else v.tobytes())
            return pa.record_batch([pa.array(out["range"], pa.int32()), *[pa.array(out[k], pa.binary()) for k in list(out)[1:]]], list(out))

        for b in source:
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                raw = text.as_py()
                codes = word_codes(raw, key)
                if len(codes) < window:
                    continue
                h = runs(codes, window)
                cells = _cells(h, bits)
                at = np.nonzero(bitmap[cells >> np.uint64(3)] >> (np.uint8(7) - (cells & np.uint64(7)).astype(np.uint8)) & 1)[0]
                if len(at):
                    gathered.append((h[at], runs(codes, window, 1)[at].astype(np.uint32), np.full(len(at), len(ids), np.uint32), at.astype(np.uint32)))
                    ids.append(doc_id)
                    size += 20 * len(at)
                if size > GATHER or len(ids) == 60_000:
                    yield sent()
                    gathered, ids, size = [], [], 0
        if gathered:
            yield sent()

    def exact(part: tuple, tables: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        h, g, doc, start = [], [], [], []
        for b in tables:
            for i in range(b.num_rows):
                column = lambda k, kind: np.frombuffer(b.column(k)[i].as_buffer(), kind)  # noqa: B023, E731
                h.append(column("h", np.uint64))
                g.append(column("g", np.uint32))
                doc.append(column("ids", np.int64)[column("doc", np.uint16)])
                start.append(column("low", np.uint16).astype(np.uint32) | column("high", np.uint16).astype(np.uint32) << np.uint32(16))
        h, g, doc, start = map(np.concatenate, (h, g, doc, start))
        if part[0].as_py() < ranges:
            order, least = least_ids(h, g, doc)
            late = order[doc[order] > least]
            if not len(late):
                return
            doc, start = doc[late], start[late]
        bucket = bucket_of(doc)
        order = np.lexsort((start, doc, bucket))
        bucket, doc, start = bucket[order], doc[order], start[order]
        out: dict[str, list] = {k: [] for k in ("bucket", "docs", "counts", "starts")}
        cut = np.nonzero(np.diff(bucket, prepend=-1))[0]
        for a, b in zip(cut, np.append(cut[1:], len(bucket)), strict=True):
            names, counts = np.unique(doc[a:b], return_counts=True)
            for k, x in zip(out, (int(bucket[a]), names.tobytes(), counts.astype(np.uint32).tobytes(), start[a:b].tobytes()), strict=True):
                out[k].append(x)
        yield pa.record_batch([pa.array(out["bucket"], pa.int32()), *[pa.array(out[k], pa.binary()) for k in list(out)[1:]]], list(out))

    def merged(tables: pa.Table) -> pa.Table:
        doc, start = [], []
        for docs_, counts, starts in zip(tables["docs"], tables["counts"], tables["starts"], strict=True):
            doc.append(np.repeat(np.frombuffer(docs_.as_buffer(), np.int64), np.frombuffer(counts.as_buffer(), np.uint32)))
            start.append(np.frombuffer(starts.as_buffer(), np.uint32))
        doc, start = np.concatenate(doc), np.concatenate(start).astype(np.int64)
        order = np.lexsort((start, doc))
        doc, start = doc[order], start[order]
        new = np.ones(len(doc), bool)  # a run ends where the next window starts beyond it, or with the document
        new[1:] = (doc[1:] != doc[:-1]) | (start[1:] > start[:-1] + window)
        begin, last = np.nonzero(new)[0], np.append(np.nonzero(new)[0][1:], len(doc)) - 1
        pairs = np.stack([start[begin], start[last] + window], axis=1).astype(np.uint32)
        names, at = np.unique(doc[begin], return_index=True)
        runs_ = [pairs[a:b].tobytes() for a, b in zip(at, np.append(at[1:], len(pairs)), strict=True)]
        return pa.table({"doc_id": pa.array(names, pa.int64()), "runs": pa.array(runs_, pa.binary())})

    packed = rows.mapInArrow(lean(candidates), "range int, h binary, g binary, doc binary, low binary, high binary, ids binary")
    found = packed.groupBy("range").applyInArrow(lean(exact), "bucket int, docs binary, counts binary, starts binary")
    return found.groupBy("bucket").applyInArrow(merged, "doc_id long, runs binary")


def covered(words: int, runs_: bytes) -> np.ndarray:
    """Which of a number of words the runs cover."""
    edge = np.zeros(words + 1, np.int32)
    pairs = np.frombuffer(runs_, np.uint32).reshape(-1, 2).astype(np.int64)
    np.add.at(edge, pairs[:, 0], 1)
    np.add.at(edge, np.minimum(pairs[:, 1], words), -1)
    return np.cumsum(edge[:-1]) > 0


def remove_repeats(docs: DataFrame, window: int = 13, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 (and the kept text) for each row.

    A word goes if a window over it also starts in a row with a smaller id; windows are judged on the input.
    Words end at ASCII white space. Null and empty texts have no words; rows with a null id keep all words and
    take none from others; rows that share an id take none from each other, nor do the windows of one text. An
    empty table gives an empty result; other columns are not read.
    """
    # Stored, so that heaps can be shrunk before texts are read again: the pairs take little.
    found = written(repeats(docs, window, id_col, text_col), "repeats")
    shrink_heaps(docs.sparkSession)
    joined = _rows(docs, id_col, text_col).join(found, "doc_id", "left").select("doc_id", "text", "runs")

    def keep(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in source:
            n, gone, digest, kept = [], [], [], []
            for text, gone_runs in zip(b.column(1), b.column(2).to_pylist(), strict=True):
                words = text.as_py().split()
                n.append(len(words))
                if gone_runs:
                    out = covered(len(words), gone_runs)
                    gone.append(int(out.sum()))
                    words = [words[i] for i in np.nonzero(~out)[0]]
                else:
                    gone.append(0)
                text = b" ".join(words)
                digest.append(hashlib.sha256(text).hexdigest())
                kept.append(text if with_text else b"")
            columns = [b.column(0), pa.array(n, pa.int64()), pa.array(gone, pa.int64()), pa.array(digest, pa.string()), pa.array(kept, pa.binary())]
            yield pa.record_batch(columns, ["doc_id", "n_words", "n_removed", "kept_sha256", "kept"])

    out = joined.mapInArrow(lean(keep), "doc_id long, n_words long, n_removed long, kept_sha256 string, kept binary")
    return out.withColumn("kept", F.col("kept").cast("string")) if with_text else out.drop("kept")
