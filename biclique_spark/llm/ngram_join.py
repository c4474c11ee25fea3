"""Jaccard join on word n-grams by token-combination prefixes.

A document's tokens are its distinct n-grams, as 64-bit hashes. Tokens have one global order: first those with a
low hash that at most RARE documents have, by hash; then the frequent ones of these, by hash; then the rest.

Let a set have n tokens, of which a partner may lack d = n - ceil(t n). Two linked sets share one of their first
d + 1 tokens. If that token is rare, the pair meets in the token's bucket: rare tokens are indexed one by one, EXTRA beyond the
prefix. Of the first r rare tokens of a set at least r - d are shared if its list ends before the partner's, so pairs
that share fewer than both sides ask for are dropped unread.
If it is frequent, both prefixes reach into the frequent tokens, and rare ones were all among the first d + 1.
Then prefixes are extended. Linked sets differ in at most s = floor((1 - t) / t n) tokens; of the first d + s + 2
tokens at least s + 2 are shared, so two shared ones stand side by side in both: frequent tokens are
indexed as combinations of two neighbours, which is as many keys as tokens. No link is lost, and a passage that
many documents share is not compared unless they share neighbours at the same place of the order.

Buckets of rare tokens are small and give their pairs. In a bucket of a combination each member is compared
with one pivot (the member with the fewest rare tokens), then with other pivots while components still part
it, and at last the pairs between its components that are left. Candidates are verified on whole texts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from biclique_spark.llm.common import discard, lean, setting, size_of, small, unused, written
from biclique_spark.llm.words import mixed, new_key, runs, word_codes

#: Documents that a rare token may have; tokens below this share of all hashes are counted.
RARE, COUNTED = 16, 0.34
#: Tokens a counting task gets about; bytes of text gathered before tokens are sent on; rounds of pivots.
SHARE, GATHER, PIVOTS = 1 << 19, 1 << 23, 1
#: Documents of a block of the last comparison; a column with more pairs than this is multiplied densely.
BLOCK, DENSE = 2048, 40_000
#: Rare tokens indexed beyond the prefix: a pair must share about so many, or it is no candidate.
EXTRA = 24
#: Rows and bytes of an Arrow batch; a row may hold two texts.
BATCH_ROWS, BATCH_BYTES = 1000, "8m"
_LOW = np.uint64(int(COUNTED * 2**64))


def shingles(text: bytes, n: int, key: bytes) -> np.ndarray:
    """The set: sorted distinct hashes of the n-grams of a text whose A-Z are lower-cased."""
    return np.unique(runs(word_codes(text, key, lower=True), n))


def linked(shared: np.ndarray, a: np.ndarray, b: np.ndarray, percent: int) -> np.ndarray:
    return 100 * shared >= percent * (a + b - shared)


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).cast("binary").alias("text"))


def sets(rows: DataFrame, n: int, key: bytes) -> DataFrame:
    """(doc_id, n, digest): how many tokens each row has, and 128 bits that equal sets share."""

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in source:
            size, digest = [], []
            for text in b.column(1):
                s = shingles(text.as_py(), n, key)
                size.append(len(s))
                digest.append(xxhash.xxh3_128_digest(s.tobytes()))
            yield pa.record_batch([b.column(0), pa.array(size, pa.int64()), pa.array(digest, pa.binary())], ["doc_id", "n", "digest"])

    return rows.mapInArrow(lean(run), "doc_id long, n long, digest binary")


def _lengths(n: int, percent: int) -> tuple[int, int]:
    """The prefix and the extended prefix of a set of n tokens."""
    lacking = n - -(-percent * n // 100)
    return lacking + 1, min(n, lacking + (100 - percent) * n // percent + 2)


def counted_tokens(rows: DataFrame, n: int, percent: int, ranges: int, key: bytes) -> DataFrame:
    """(doc_id, n, low, tokens): a row for each document and range, with those tokens of the (extended) prefix's
    region that another document has too. ``tokens`` are records of token, place by hash and whether it is frequent.

    A token that more than RARE documents of a chunk have is frequent: its documents learn it at once, and only its
    count goes to the token's range, so that no range gets more than RARE entries of a token from a chunk.
    """
    record = np.dtype([("token", np.uint64), ("place", np.uint32), ("frequent", np.uint8)])

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ("range", "token", "doc", "place", "high", "many", "ids", "sizes", "lows")
        ids, sizes, lows, gathered, size = [], [], [], [], 0

        def sent() -> pa.RecordBatch:
            token = np.concatenate([x[0] for x in gathered])
            doc = np.repeat(np.arange(len(gathered), dtype=np.uint16), [len(x[0]) for x in gathered])
            place = np.concatenate([x[1] for x in gathered])
            all_ids, all_sizes, all_lows = np.array(ids, np.int64), np.array(sizes, np.uint32), np.array(lows, np.uint32)
            order = np.argsort(token, kind="stable")
            token, doc, place = token[order], doc[order], place[order]
            first = np.ones(len(token), bool)
            first[1:] = token[1:] != token[:-1]
            at = np.nonzero(first)[0]
            count = np.diff(np.append(at, len(token)))
            many = np.repeat(count > RARE, count)
            out: dict[str, list] = {k: [] for k in names}

            def put(r: int, own: np.ndarray, counts: np.ndarray | None) -> None:
                used, back = np.unique(doc[own], return_inverse=True) if counts is None else (np.zeros(0, int), np.zeros(0, int))
                values = (
                    r, token[own].tobytes(), back.astype(np.uint16).tobytes(), (place[own] & 0xFFFF).astype(np.uint16).tobytes() if counts is None else b"",
                    (place[own] >> 16).astype(np.uint16).tobytes() if counts is None else b"", b"" if counts is None else counts.astype(np.uint32).tobytes(),
                    all_ids[used].tobytes(), all_sizes[used].tobytes(), all_lows[used].tobytes(),
                )
                for k, x in zip(names, values, strict=True):
                    out[k].append(x)

            where = (token & np.uint64(ranges - 1)).astype(np.int64)
            # Entries of locally frequent tokens go back by document, in as many groups as there are ranges.
            where = np.where(many, ranges + doc.astype(np.int64) % ranges, where)
            by = np.argsort(where, kind="stable")
            cut = np.nonzero(np.diff(where[by], prepend=-1))[0]
            for a, b in zip(cut, np.append(cut[1:], len(by)), strict=True):
                put(int(where[by[a]]), by[a:b], None)
            heads = at[count > RARE]
            to = (token[heads] & np.uint64(ranges - 1)).astype(np.int64)
            for r in np.unique(to):
                put(int(r), heads[to == r], count[count > RARE][to == r])
            return pa.record_batch([pa.array(out["range"], pa.int32()), *[pa.array(out[k], pa.binary()) for k in names[1:]]], list(names))

        for b in source:
            for doc_id, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                raw = text.as_py()
                s = shingles(raw, n, key)
                if not len(s):
                    continue
                low = int(np.searchsorted(s, _LOW))
                most = max(low, _lengths(len(s), percent)[1])
                gathered.append((s[:most], np.arange(most, dtype=np.uint32)))
                ids.append(doc_id)
                sizes.append(len(s))
                lows.append(low)
                size += len(raw)
                if size > GATHER or len(ids) == 60_000:
                    yield sent()
                    ids, sizes, lows, gathered, size = [], [], [], [], 0
        if gathered:
            yield sent()

    def count(part: tuple, tables: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        entries, known = [], []
        for b in tables:
            for i in range(b.num_rows):
                column = lambda k, kind: np.frombuffer(b.column(k)[i].as_buffer(), kind)  # noqa: B023, E731
                if len(many := column("many", np.uint32)):
                    known.append((column("token", np.uint64), many))
                    continue
                doc = column("doc", np.uint16)
                place = column("place", np.uint16).astype(np.uint32) | column("high", np.uint16).astype(np.uint32) << np.uint32(16)
                entries.append((column("token", np.uint64), place, column("ids", np.int64)[doc], column("sizes", np.uint32)[doc], column("lows", np.uint32)[doc]))
        if not entries:
            return
        token, place, doc, size, low = map(np.concatenate, zip(*entries, strict=True))
        if part[0].as_py() >= ranges:
            frequent = np.ones(len(token), bool)
        else:
            all_tokens = np.concatenate([token, *[x[0] for x in known]])
            weights = np.concatenate([np.ones(len(token), np.int64), *[x[1] for x in known]])
            values, back = np.unique(all_tokens, return_inverse=True)
            df = np.bincount(back, weights, len(values))[back[: len(token)]]
            keep = df > 1
            token, place, doc, size, low, frequent = (x[keep] for x in (token, place, doc, size, low, df > RARE))
        if not len(token):
            return
        order = np.lexsort((place, doc))
        packed = np.empty(len(token), record)
        packed["token"], packed["place"], packed["frequent"] = token[order], place[order], frequent[order]
        names, at = np.unique(doc[order], return_index=True)
        own = [packed[a:b].tobytes() for a, b in zip(at, np.append(at[1:], len(packed)), strict=True)]
        columns = [pa.array(names), pa.array(size[order][at].astype(np.int64)), pa.array(low[order][at].astype(np.int64)), pa.array(own, pa.binary())]
        yield pa.record_batch(columns, ["doc_id", "n", "low", "tokens"])

    schema = "range int, token binary, doc binary, place binary, high binary, many binary, ids binary, sizes binary, lows binary"
    return rows.mapInArrow(lean(run), schema).groupBy("range").applyInArrow(lean(count), "doc_id long, n long, low long, tokens binary")


def index(counted: DataFrame, percent: int) -> DataFrame:
    """(key, pair, doc_id, n, own, need): the keys of each document; ``pair`` marks combinations, ``own`` is its number of
    rare tokens, ``need`` how many of its indexed rare tokens a partner shares at least."""
    record = np.dtype([("token", np.uint64), ("place", np.uint32), ("frequent", np.uint8)])

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in source:
            key, pair, doc, size, own, need = [], [], [], [], [], []
            for doc_id, n, low, parts in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3), strict=True):
                t = np.concatenate([np.frombuffer(x.as_buffer(), record) for x in parts])
                t = t[np.argsort(t["place"], kind="stable")]
                prefix, longer = _lengths(n, percent)
                inside = t["place"] < low
                often = inside & (t["frequent"] > 0)
                rare = int(low - often.sum())
                at = t["place"].astype(np.int64) - (np.cumsum(often) - often)
                single = t["token"][inside & ~often & (at < prefix + EXTRA)]
                combined = np.zeros(0, np.uint64)
                if rare < prefix:
                    tail = np.concatenate([t["token"][often], t["token"][~inside]])
                    where = np.concatenate([rare + np.arange(often.sum()), t["place"][~inside].astype(np.int64)])
                    tail = tail[where < longer]
                    combined = mixed(tail[:-1] * np.uint64(0xD1342543DE82EF95) + tail[1:])
                for keys, kind in ((single, False), (combined, True)):
                    key.append(keys)
                    pair.append(np.full(len(keys), kind))
                m = len(single) + len(combined)
                doc.append(np.full(m, doc_id, np.int64))
                size.append(np.full(m, n, np.int64))
                own.append(np.full(m, rare, np.int64))
                need.append(np.full(m, max(1, min(rare, prefix + EXTRA) - prefix + 1), np.int64))
            if key:
                columns = [np.concatenate(key).view(np.int64), np.concatenate(pair), *map(np.concatenate, (doc, size, own, need))]
                yield pa.record_batch(list(map(pa.array, columns)), ["key", "pair", "doc_id", "n", "own", "need"])

    whole = counted.groupBy("doc_id", "n", "low").agg(F.collect_list("tokens").alias("tokens"))
    return whole.mapInArrow(lean(run), "key long, pair boolean, doc_id long, n long, own long, need long")


def _near(percent: int, a: str = "n_a", b: str = "n_b"):
    """Sets whose sizes alone don't rule a link out."""
    return 100 * F.least(a, b) >= percent * F.greatest(a, b)


def rare_pairs(keys: DataFrame, percent: int) -> DataFrame:
    """(a, b) that share as many rare tokens as their sets ask for. A bucket holds RARE members at most."""
    members = keys.where("not pair").groupBy("key").agg(F.sort_array(F.collect_list(F.struct("doc_id", "n", "need"))).alias("m")).where("size(m) > 1")
    each = members.select("m", F.posexplode("m").alias("at", "x"))
    both = each.select("x", F.explode(F.slice("m", F.col("at") + 2, F.size("m"))).alias("y"))
    both = both.select(F.col("x.doc_id").alias("a"), F.col("x.n").alias("n_a"), F.col("y.doc_id").alias("b"), F.col("y.n").alias("n_b"), F.least("x.need", "y.need").alias("need"))
    return both.where(_near(percent)).groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared"), F.max("need").alias("need")).where("shared >= need").select("a", "b")


def pivot_pairs(combined: DataFrame, comp: DataFrame | None, percent: int, turn: int) -> DataFrame:
    """(a, b) of each bucket's pivot and the members that are not in its component yet."""
    rank = F.struct("own", "doc_id") if turn == 0 else F.struct(F.md5(F.concat_ws(":", F.lit(turn), F.col("doc_id").cast("string"))), "doc_id")
    if comp is not None:
        combined = combined.join(comp, "doc_id", "left").withColumn("comp", F.coalesce("comp", "doc_id"))
        several = combined.groupBy("key").agg(F.min("comp").alias("x"), F.max("comp").alias("y")).where("x < y").select("key")
        combined = combined.join(several, "key", "left_semi")
    else:
        combined = combined.withColumn("comp", F.col("doc_id"))
    pivot = combined.groupBy("key").agg(F.min_by(F.struct("doc_id", "n", "comp"), rank).alias("p"))
    both = combined.join(pivot, "key").where("p.doc_id <> doc_id and p.comp <> comp")
    both = both.select(F.col("p.doc_id").alias("p"), F.col("p.n").alias("n_a"), F.col("doc_id").alias("d"), F.col("n").alias("n_b")).where(_near(percent))
    return both.select(F.least("p", "d").alias("a"), F.greatest("p", "d").alias("b")).distinct()


def overlaps(a: list[np.ndarray], b: list[np.ndarray]) -> np.ndarray:
    """How many tokens each set of a shares with each of b: tokens that many of both have by products of dense
    columns, the others pair by pair."""
    tokens_a, tokens_b = np.concatenate(a), np.concatenate(b)
    common = np.intersect1d(np.unique(tokens_a), np.unique(tokens_b), assume_unique=True)
    out = np.zeros((len(a), len(b)), np.float32)
    if not len(common):
        return out

    def places(tokens: np.ndarray, sets_: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        at = np.minimum(np.searchsorted(common, tokens), len(common) - 1)
        here = common[at] == tokens
        doc = np.repeat(np.arange(len(sets_)), [len(x) for x in sets_])
        order = np.argsort(at[here], kind="stable")
        return at[here][order], doc[here][order]

    (col_a, doc_a), (col_b, doc_b) = places(tokens_a, a), places(tokens_b, b)
    n_a, n_b = np.bincount(col_a, minlength=len(common)), np.bincount(col_b, minlength=len(common))
    heavy = n_a * n_b > DENSE
    which = np.nonzero(heavy)[0]
    name = np.full(len(common), -1)
    name[which] = np.arange(len(which))
    for at in range(0, len(which), 1024):
        halves = []
        for col, doc, n in ((col_a, doc_a, len(a)), (col_b, doc_b, len(b))):
            here = (name[col] >= at) & (name[col] < at + 1024)
            m = np.zeros((n, min(1024, len(which) - at)), np.float32)
            m[doc[here], name[col[here]] - at] = 1
            halves.append(m)
        out += halves[0] @ halves[1].T
    first_b = np.concatenate([[0], np.cumsum(n_b)])
    light = np.nonzero(~heavy[col_a])[0]
    for at in range(0, len(light), 1 << 14):
        own = light[at : at + (1 << 14)]
        times = n_b[col_a[own]]
        row = np.repeat(doc_a[own], times)
        within = np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
        column = doc_b[np.repeat(first_b[col_a[own]], times) + within]
        out += np.bincount(row * len(b) + column, minlength=out.size).reshape(out.shape).astype(np.float32)
    return out


def parted_links(combined: DataFrame, comp: DataFrame, rows: DataFrame, n: int, percent: int, key: bytes) -> DataFrame:
    """(a, b): links between components that still share a bucket, enough of them to join what is linked.

    Buckets that meet form clusters. In a cluster each document outside its largest component is compared with all
    others, block by block of hashed ids: a task holds two blocks of sets and returns, for each document, one link to
    each other component. Rows grow with the number of blocks, never with pairs.
    """
    named = combined.join(comp, "doc_id", "left").withColumn("comp", F.coalesce("comp", "doc_id"))
    several = named.groupBy("key").agg(F.min("comp").alias("x"), F.max("comp").alias("y"), F.min("doc_id").alias("head")).where("x < y").select("key", "head")
    named = named.join(several, "key").select("doc_id", "comp", "head").distinct()
    named = written(named, "ngram-parted")
    apart = named.select("doc_id", "comp").distinct()
    cluster = components(named.where("doc_id <> head").select(F.col("head").alias("a"), F.col("doc_id").alias("b")))
    apart = apart.join(cluster.withColumnRenamed("comp", "cluster"), "doc_id")
    sizes = apart.groupBy("cluster", "comp").agg(F.count(F.lit(1)).alias("m"))
    sizes = sizes.groupBy("cluster").agg(F.max_by("comp", F.struct("m", "comp")).alias("largest"), F.sum("m").alias("whole"), F.max("m").alias("most"))
    apart = apart.join(sizes, "cluster")
    many = lambda c: F.ceil(c / F.lit(BLOCK)).cast("long")
    hashed = F.xxhash64("doc_id")
    of_all, of_rest = many(F.col("whole")), F.greatest(F.lit(1).cast("long"), many(F.col("whole") - F.col("most")))

    def packed(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in source:
            sets_ = [shingles(t.as_py(), n, key).tobytes() for t in b.column(1)]
            yield pa.record_batch([b.column(0), pa.array(sets_, pa.binary())], ["doc_id", "tokens"])

    wanted = rows.join(small(apart.select("doc_id")), "doc_id", "left_semi").mapInArrow(lean(packed), "doc_id long, tokens binary")
    full = written(wanted.join(apart, "doc_id"), "ngram-blocks")
    one = full.where("comp <> largest").select("cluster", F.pmod(hashed, of_rest).alias("i"), F.explode(F.sequence(F.lit(0).cast("long"), of_all - 1)).alias("j"), F.lit(True).alias("asks"), "doc_id", "comp", "tokens")
    all_ = full.select("cluster", F.explode(F.sequence(F.lit(0).cast("long"), of_rest - 1)).alias("i"), F.pmod(hashed, of_all).cast("long").alias("j"), F.lit(False).alias("asks"), "doc_id", "comp", "tokens")

    def compare(tables: pa.Table) -> pa.Table:
        asks = tables["asks"].to_numpy()
        ids, comps = tables["doc_id"].to_numpy(), tables["comp"].to_numpy()
        sets_ = [np.frombuffer(x.as_buffer(), np.uint64) for x in tables["tokens"]]
        a, b = np.nonzero(asks)[0], np.nonzero(~asks)[0]
        if not len(a) or not len(b):
            return pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64())})
        shared = overlaps([sets_[i] for i in a], [sets_[i] for i in b]).astype(np.int64)
        n_a, n_b = np.array([len(sets_[i]) for i in a]), np.array([len(sets_[i]) for i in b])
        hit = linked(shared, n_a[:, None], n_b[None, :], percent) & (comps[a][:, None] != comps[b][None, :])
        x, y = np.nonzero(hit)
        x, y = a[x], b[y]
        _, first = np.unique(np.stack([ids[x], comps[y]]), axis=1, return_index=True)
        x, y = ids[x[first]], ids[y[first]]
        return pa.table({"a": pa.array(np.minimum(x, y), pa.int64()), "b": pa.array(np.maximum(x, y), pa.int64())})

    return one.unionByName(all_).groupBy("cluster", "i", "j").applyInArrow(compare, "a long, b long").distinct()


def verified(pairs: DataFrame, rows: DataFrame, n: int, percent: int, key: bytes) -> DataFrame:
    """The pairs that are links, by the whole texts of both."""
    wanted = pairs.select(F.col("a").alias("doc_id")).unionByName(pairs.select(F.col("b").alias("doc_id"))).distinct()
    texts = rows.join(small(wanted), "doc_id", "left_semi")
    both = pairs.join(texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a")), "a")
    both = both.join(texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b")), "b").select("a", "b", "text_a", "text_b")

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept: dict[int, np.ndarray] = {}

        def of(doc: int, text: pa.BinaryScalar) -> np.ndarray:
            if doc not in kept:
                if len(kept) > 64:
                    kept.clear()
                kept[doc] = shingles(text.as_py(), n, key)
            return kept[doc]

        for batch in source:
            fine = []
            for a, b, x, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), batch.column(3), strict=True):
                s, t = of(a, x), of(b, y)
                shared = len(np.intersect1d(s, t, assume_unique=True))
                fine.append(bool(linked(shared, len(s), len(t), percent)))
            yield pa.record_batch([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(fine, pa.bool_()))

    return both.mapInArrow(lean(run), "a long, b long")


def components(links: DataFrame) -> DataFrame:
    """(doc_id, comp): the smallest id that links reach from each end of a link. Each round takes the neighbours'
    smallest label and then the label's label, so chains shorten by half; tables cut the lineage, and each goes when
    the next is there."""
    ends = written(links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "ngram-ends")
    label = written(ends.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("comp")), "ngram-label")
    while True:
        seen = ends.join(label.select(F.col("a").alias("b"), F.col("comp").alias("theirs")), "b").groupBy("a").agg(F.min("theirs").alias("theirs"))
        new = label.select("a", "comp").join(seen, "a").select("a", F.least("comp", "theirs").alias("comp"), F.col("comp").alias("old"))
        jump = label.select(F.col("a").alias("comp"), F.col("comp").alias("further"))
        new = new.join(jump, "comp", "left").select("a", F.least("comp", F.coalesce("further", "comp")).alias("comp"), "old")
        new = written(new, "ngram-label")
        discard(label)
        label = new
        if not new.where("comp <> old").limit(1).count():
            discard(ends)
            return label.select(F.col("a").alias("doc_id"), "comp")


def join_components(docs: DataFrame, n: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id for each row.

    Two rows link when 100 * shared >= percent * all of their sets' tokens; with fewer than n words the whole
    sequence is the one token. Rows without words link with nothing, nor do rows with a null id (their component
    is null). Equal sets link; repeated rows have one component. An empty table gives an empty result; other
    columns are not read. Very long texts are read whole; hashes have 64 bits.
    """
    with setting(docs.sparkSession, spark__sql__execution__arrow__maxRecordsPerBatch=str(BATCH_ROWS), spark__sql__execution__arrow__maxBytesPerBatch=BATCH_BYTES):
        return _join_components(docs, n, percent, id_col, text_col)


def _join_components(docs: DataFrame, n: int, percent: int, id_col: str, text_col: str) -> DataFrame:
    rows, key = _rows(docs, id_col, text_col), new_key()
    size = written(sets(rows, n, key), "ngram-sets")
    equal = size.where("n > 0 and doc_id is not null").groupBy("digest").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"))
    equal = equal.where("copies > 1").select("digest", "rep")
    same = written(size.where("n > 0 and doc_id is not null").join(equal, "digest").select("doc_id", "rep").distinct(), "ngram-same")
    # One text of each set goes on; of rows that repeat an id, each goes on with its own text.
    alone = rows.where("doc_id is not null").join(small(same.where("doc_id <> rep").select("doc_id")), "doc_id", "left_anti")
    bytes_ = size_of(docs, text_col)
    ranges = 1 << max(3, int(bytes_ // 6 * 0.4 // SHARE).bit_length())
    keys = written(index(counted_tokens(alone, n, percent, ranges, key), percent), "ngram-index")
    several = keys.groupBy("key", "pair").agg(F.min("doc_id").alias("x"), F.max("doc_id").alias("y")).where("x < y").select("key", "pair")
    combined = written(keys.where("pair").join(several.where("pair").select("key"), "key", "left_semi").drop("pair"), "ngram-combined")
    done = written(rare_pairs(keys, percent).unionByName(pivot_pairs(combined, None, percent, 0)).distinct(), "ngram-pairs")
    links = written(verified(done, alone, n, percent, key), "ngram-links")
    comp = components(links)
    for turn in range(1, PIVOTS + 1):
        pairs = written(pivot_pairs(combined, comp, percent, turn).join(done, ["a", "b"], "left_anti"), "ngram-pairs")
        found = written(verified(pairs, alone, n, percent, key), "ngram-links")
        done = done.unionByName(pairs)
        if found.limit(1).count():
            links = links.unionByName(found)
            comp = components(links)
    found = written(parted_links(combined, comp, alone, n, percent, key), "ngram-links")
    if found.limit(1).count():
        comp = components(links.unionByName(found))
    of = size.select("doc_id", F.col("n").alias("n_shingles"))
    of = of.join(same, "doc_id", "left").withColumn("rep", F.coalesce("rep", "doc_id"))
    of = of.join(comp.select(F.col("doc_id").alias("rep"), "comp"), "rep", "left")
    return of.select("doc_id", "n_shingles", F.coalesce("comp", "rep").alias("component_id"))


def keep_one(docs: DataFrame, n: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each component, with all its columns: the one with the smallest id, nulls last. Rows are judged one
    by one: where ids repeat or are null, each row gets a number of its own for the join, so a row never goes for what
    another row with its id holds. Rows without words (null or empty texts) are linked with nothing and all stay; an
    empty table gives an empty result."""
    rows, ids, distinct = docs.agg(F.count(F.lit(1)), F.count(id_col), F.count_distinct(id_col)).first()
    plain = rows == ids == distinct
    row = unused("row", docs)
    numbered = docs if plain else written(docs.withColumn(row, F.monotonically_increasing_id()), "ngram-numbered")
    found = join_components(numbered, n, percent, id_col if plain else row, text_col)
    if plain:
        gone = found.where("doc_id <> component_id").select(F.col("doc_id").alias(row))
        return docs.join(small(written(gone, "ngram-gone")), docs[id_col] == F.col(row), "left_anti")
    named = numbered.select(F.col(row).alias("doc_id"), F.col(id_col).alias("id")).join(found, "doc_id")
    best = named.groupBy("component_id").agg(F.min_by("doc_id", F.struct(F.col("id").isNull(), F.col("id"), F.col("doc_id"))).alias("best"))
    gone = named.join(best, "component_id").where("doc_id <> best").select(F.col("doc_id").alias(row))
    return numbered.join(small(written(gone, "ngram-gone")), row, "left_anti").drop(row)
