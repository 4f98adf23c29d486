"""Removal of byte strings that repeat an earlier document, by suffix arrays.

A byte goes if a string of ``length`` bytes that covers it also starts in a document
with a smaller doc_id. Phases:

1. equal texts become one (their first document); later copies go whole;
2. anchors: in every window of ``length`` bytes the smallest hashed gram
   (leftmost of equals) is the anchor, so equal windows have equal anchors at
   equal places; only anchors that two documents share can lie in a repeat;
3. the stretches of text around shared anchors (contexts) become distinct before
   they move, each with the smallest doc_id that holds it. They meet by anchor in
   shards; each shard gets a suffix array by Larsson-Sadakane refinement (prefix
   doubling that sorts only groups still unsorted, started from 8-byte keys) and
   common prefixes by Kasai's inequality; suffixes with a common prefix of ``length``
   bytes form a group whose smallest doc_id decides;
4. an anchor with more distinct contexts than a shard holds is dealt over several
   shards; their sorted distinct strings are brought together by string, and each
   shard finds by binary search which of its own an earlier document has elsewhere;
5. marked windows return to their documents and become maximal removed runs.

No task holds more than a shard of contexts, however often a passage occurs. Every
phase is written to the shared folder, so a lost executor repeats single tasks.

Defined results: null and empty texts have nothing to remove; rows with a null doc_id
neither remove nor lose anything; rows with the same doc_id do not affect each other;
texts shorter than ``length`` stay whole, copies too; extra columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import PrefixHash, writing, materialize, release, scratch, slices, table

#: Bytes of a gram (longer ones where a mask could not hold a bit for each of a context's windows).
GRAM, MOST_WINDOWS = 20, 62
#: Bits of an ordering key that hold a place in the batch; the rest are the hash's.
PLACE_BITS = 40
#: Bytes of distinct contexts in a shard.
SHARD = 1 << 20


def gram_bytes(length: int) -> int:
    return max(min(GRAM, length), length - MOST_WINDOWS + 1)


# ---------------------------------------------------------------- anchors


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    column = pc.fill_null(column.cast(pa.large_string()), "")
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    _, off, data = column.buffers()
    off = np.frombuffer(off, np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(data, np.uint8)[off[0] : off[-1]] if off[-1] > off[0] else np.zeros(0, np.uint8)
    return data, off - off[0]


def anchors(tools: PrefixHash, data: np.ndarray, off: np.ndarray, length: int):
    """(text, hash, first window, last window, hash of the stretch they cover) of the anchors of all windows inside single texts."""
    gram = gram_bytes(length)
    windows = length - gram + 1
    empty = np.zeros(0, np.int64)
    if len(data) < length:
        return empty, empty.astype(np.uint64), empty, empty, empty.astype(np.uint64)
    sums = tools.sums(data)
    grams = tools.grams(sums, gram)
    # smallest gram of each run of `windows` grams: the hash's top bits order, then the place (leftmost of equals),
    # so the choice depends on a window's bytes alone; minima are taken over doubling spans
    low = np.uint64((1 << PLACE_BITS) - 1)
    best, span = (grams & ~low) | np.arange(len(grams), dtype=np.uint64), 1
    while span * 2 <= windows:
        best = np.minimum(best[:-span], best[span:])
        span *= 2
    if windows > span:
        best = np.minimum(best[: -(windows - span)], best[windows - span :])
    where = (best & low).astype(np.int64)
    # windows inside single texts: all but the last `length - 1` places of each
    crossing = np.zeros(len(data) + 1, np.int32)
    np.add.at(crossing, np.maximum(off[:-1], off[1:] - length + 1), 1)
    np.add.at(crossing, off[1:], -1)
    n = np.flatnonzero(np.cumsum(crossing)[: len(where)] == 0)
    where = where[n]
    new = np.ones(len(n), bool)
    new[1:] = where[1:] != where[:-1]
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(n))[: len(first)] - 1
    doc = np.searchsorted(off, n[first], "right") - 1
    return doc, grams[where[first]], n[first], n[last], tools.ranges(sums, n[first], n[last] + length)


# ---------------------------------------------------------------- suffix arrays


def suffix_array(data: np.ndarray, depth: int) -> np.ndarray:
    """Positions of data in the order of their suffixes' first `depth` bytes or more.

    Ranks start from packed 8-byte keys; every round doubles the sorted prefix and
    sorts only the members of groups that are still equal.
    """
    n = len(data)
    key = packed(data)
    sa = np.argsort(key)
    rank = np.empty(n + 1, np.int64)
    rank[n] = -1
    new = np.ones(n, bool)
    new[1:] = key[sa[1:]] != key[sa[:-1]]
    group = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    rank[sa] = group
    sorted_to = 8
    while sorted_to < depth:
        alone = new & np.append(new[1:], True)
        slots = np.flatnonzero(~alone)
        if not len(slots):
            break
        suffix = sa[slots]
        both = group[slots] * np.int64(n + 1) + rank[np.minimum(suffix + sorted_to, n)] + 1  # group, then what follows
        order = np.argsort(both)
        suffix, both = suffix[order], both[order]
        sa[slots] = suffix
        new[slots[1:]] |= both[1:] != both[:-1]
        group = np.maximum.accumulate(np.where(new, np.arange(n), 0))
        rank[sa] = group
        sorted_to *= 2
    return sa


def packed(data: np.ndarray) -> np.ndarray:
    """The eight bytes from every position as one big-endian number (zeros past the end)."""
    wide = np.zeros(len(data) + 8, np.uint64)
    wide[: len(data)] = data
    out = wide[: len(data)].copy()
    for i in range(1, 8):
        out = (out << np.uint64(8)) | wide[i : len(data) + i]
    return out


def common_prefixes(data: np.ndarray, sa: np.ndarray, most: int, stride: int = 16) -> np.ndarray:
    """Common prefix length (up to `most`) of each suffix in sa with the one before it; sa may leave suffixes out.

    Kasai's inequality in vector form: the prefix at a position is at least that of the
    position before less one, so every `stride`-th position of a run of listed positions is
    compared from scratch and the others start from what those leave (where the suffix that
    the first was compared with has its followers listed, too).
    """
    n = len(data)
    listed = np.zeros(n + 1, bool)
    listed[sa] = True
    run = np.maximum.accumulate(np.where(listed[:n] & ~np.append(False, listed[: n - 1]), np.arange(n), 0)) if n else np.zeros(0, int)
    before = np.full(n, -1)
    before[sa[1:]] = sa[:-1]
    wide = np.concatenate([data.astype(np.int16), np.full(most + stride + 8, -1, np.int16)])
    key = packed(data)
    plcp = np.zeros(n, np.int64)

    def extend(at, least):
        at_ = before[at]
        out = np.where(at_ < 0, 0, least)
        live = np.flatnonzero(at_ >= 0)
        while len(live):  # eight bytes at a time
            p, q = at[live] + out[live], at_[live] + out[live]
            ok = (out[live] < most) & (np.maximum(p, q) + 8 <= n)
            same = np.zeros(len(live), bool)
            same[ok] = key[p[ok]] == key[q[ok]]
            out[live[same]] += 8
            live = live[same]
        live = np.flatnonzero((at_ >= 0) & (out < most))
        for _ in range(8):
            p, q = at[live] + out[live], at_[live] + out[live]
            same = (wide[p] == wide[q]) & (wide[p] >= 0)
            live = live[same]
            out[live] += 1
            if not len(live):
                break
        return np.minimum(out, most)

    at = np.flatnonzero(listed[:n])
    step = (at - run[at]) % stride
    base, rest, step = at[step == 0], at[step > 0], step[step > 0]
    plcp[base] = extend(base, np.zeros(len(base), np.int64))
    other, left = before[rest - step], plcp[rest - step]
    beside = np.minimum(other + step, n)
    known = (other >= 0) & listed[beside] & (run[np.minimum(beside, n - 1)] == run[other])
    # a prefix cut at `most` may be longer than the sorted depth, where order and so the inequality end
    plcp[rest] = extend(rest, np.where(known & (left < most), np.maximum(0, left - step), 0))
    return plcp[sa]


def shard_minima(data: np.ndarray, valid: np.ndarray, owner: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(window places, their group, smallest owner of each group) for the valid window starts of a shard."""
    sa = suffix_array(data, length)
    sa = sa[valid[sa]]
    if not len(sa):
        return sa, sa, owner[:0]
    group = np.cumsum(common_prefixes(data, sa, length) < length)
    start = np.flatnonzero(np.append(True, group[1:] != group[:-1]))
    low = np.minimum.reduceat(owner[sa], start)
    return sa, np.repeat(np.arange(len(start)), np.diff(np.append(start, len(sa)))), low


class Shard:
    """Contexts laid end to end, with their windows' owners."""

    def __init__(self, contexts: list[bytes], docs: np.ndarray, length: int):
        size = np.array([len(c) for c in contexts])
        self.length, self.docs = length, docs
        self.data = np.frombuffer(b"".join(contexts), np.uint8)
        self.start = np.cumsum(size) - size
        self.row = np.repeat(np.arange(len(size)), size)
        self.inside = np.arange(len(self.data)) - self.start[self.row]
        self.valid = self.inside <= size[self.row] - length
        self.place, self.group, self.low = shard_minima(self.data, self.valid, docs[self.row], length)

    def strings(self) -> np.ndarray:
        """The sorted distinct windows, one row of bytes each."""
        first = self.place[np.flatnonzero(np.append(True, self.group[1:] != self.group[:-1]))] if len(self.place) else self.place
        return self.data[first[:, None] + np.arange(self.length)]

    def masks(self) -> np.ndarray:
        """For every context, a bit for each window that an earlier document has."""
        hit = self.low[self.group] < self.docs[self.row[self.place]]
        place = self.place[hit]
        out = np.zeros(len(self.docs), np.int64)
        np.bitwise_or.at(out, self.row[place], np.int64(1) << self.inside[place])
        return out


def as_keys(strings: np.ndarray) -> np.ndarray:
    """Rows of bytes as comparable values; a last byte of one keeps zero bytes at the end from being taken for padding."""
    return np.ascontiguousarray(np.pad(strings, ((0, 0), (0, 1)), constant_values=1)).view(f"S{strings.shape[1] + 1}").ravel()


# ---------------------------------------------------------------- phases


def distinct_texts(docs: DataFrame, length: int) -> tuple[DataFrame, DataFrame]:
    """(rows, firsts): every row's doc_id, sha and size; the first doc_id of every text of at least `length` bytes."""
    rows = materialize(docs.select("doc_id", F.unhex(F.sha2(F.coalesce("text", F.lit("")), 256)).alias("sha"), F.octet_length(F.coalesce("text", F.lit(""))).cast("long").alias("n_bytes")), "sa-rows")
    firsts = rows.where((F.col("n_bytes") >= length) & F.col("doc_id").isNotNull()).groupBy("sha").agg(F.min("doc_id").alias("doc_id"))
    return rows, firsts


def find_anchors(length: int):
    """The distinct anchors of rows (doc_id, text)."""

    def run(batches):
        tools = PrefixHash()
        for whole in batches:
            for b in slices(whole, "text"):
                doc, h, *_ = anchors(tools, *text_bytes(b.column(1)), length)
                order = np.lexsort((h, doc))
                doc, h = doc[order], h[order]
                new = np.ones(len(h), bool)
                new[1:] = (doc[1:] != doc[:-1]) | (h[1:] != h[:-1])
                yield pa.RecordBatch.from_arrays([pa.array(h[new].astype(np.int64)), b.column(0).take(pa.array(doc[new]))], names=["anchor", "doc_id"])

    return run


def cut_contexts(length: int):
    """The distinct contexts of rows (doc_id, text, sid, anchors) at those anchors, with all their places."""

    def run(batches):
        tools = PrefixHash()
        for whole in batches:
            for b in slices(whole, "text"):
                data, off = text_bytes(b.column(1))
                doc, h, first, last, ctx = anchors(tools, data, off, length)
                h, ctx = h.astype(np.int64), ctx.astype(np.int64)
                edge = np.searchsorted(doc, np.arange(b.num_rows + 1))
                keep = np.concatenate([np.isin(h[a:z], b.column(3)[i].values.to_numpy()) for i, (a, z) in enumerate(zip(edge[:-1], edge[1:], strict=True))] or [np.zeros(0, bool)])
                order = np.flatnonzero(keep)
                order = order[np.lexsort((first[order], ctx[order], h[order], doc[order]))]
                doc, h, first, last, ctx = doc[order], h[order], first[order], last[order], ctx[order]
                new = np.ones(len(h), bool)
                new[1:] = (doc[1:] != doc[:-1]) | (h[1:] != h[:-1]) | (ctx[1:] != ctx[:-1])
                at = np.flatnonzero(new)
                places = pa.ListArray.from_arrays(pa.array(np.append(at, len(h)), pa.int32()), pa.array(first - off[doc]))
                raw = data.tobytes()
                context = [raw[a : z + length] for a, z in zip(first[at].tolist(), last[at].tolist(), strict=True)]
                pick = pa.array(doc[at])
                yield pa.RecordBatch.from_arrays([pa.array(h[at]), pa.array(ctx[at]), b.column(0).take(pick), b.column(2).take(pick), places, pa.array(context, pa.binary())], names=["anchor", "ctx", "doc_id", "sid", "at", "context"])

    return run


JUDGED = "anchor long, ctx long, owner long, hi long, below long, whole long"


def verdict_rows(cols, below: np.ndarray, length: int) -> pa.RecordBatch:
    """Rows of JUDGED for contexts (anchor, ctx, owner, hi, context); those that cost no document a byte are left out."""
    size = pc.binary_length(cols[4]).to_numpy(zero_copy_only=False).astype(np.int64)
    whole = (np.int64(1) << (size - length + 1)) - 1
    keep = (below != 0) | (cols[3].to_numpy() > cols[2].to_numpy())
    return pa.RecordBatch.from_arrays([*cols[:4], pa.array(below), pa.array(whole)], names=["anchor", "ctx", "owner", "hi", "below", "whole"]).filter(pa.array(keep))


def judge_sorted(length: int):
    """Verdicts over contexts in the order of their anchors, a shard at a time; no anchor here has more than a shard."""

    def work(cols):
        anchor = cols[0].to_numpy()
        edge = np.flatnonzero(np.append(True, anchor[1:] != anchor[:-1]))
        size = np.diff(np.append(edge, len(anchor)))
        mixed = np.flatnonzero(np.repeat(size, size) > 1)  # one context alone needs no sorting
        below = np.zeros(len(anchor), np.int64)
        if len(mixed):
            below[mixed] = Shard(cols[4].take(pa.array(mixed)).to_pylist(), cols[2].to_numpy()[mixed], length).masks()
        return verdict_rows(cols, below, length)

    def run(batches):
        hold: list[tuple] = []
        size = 0
        for b in batches:
            if not b.num_rows:
                continue
            hold.append(tuple(b.columns))
            size += b.column(4).nbytes
            if size < SHARD:
                continue
            cols = [pa.concat_arrays([h[i] for h in hold]) for i in range(5)]
            a = cols[0].to_numpy()
            end = int(np.searchsorted(a, a[-1]))  # the last anchor may go on in the next batch
            if end:
                yield work([c.slice(0, end) for c in cols])
            # copied, so that what is done with can be freed
            hold = [tuple(c.slice(end).take(pa.array(np.arange(len(c) - end))) for c in cols)]
            size = hold[0][4].nbytes if end else 0
        if hold and len(cols := [pa.concat_arrays([h[i] for h in hold]) for i in range(5)]):
            yield work(cols)

    return run


def judge_large(rows: DataFrame, length: int) -> DataFrame:
    """Verdicts over contexts (anchor, ctx, owner, hi, context, shard) of anchors that take several shards."""

    def shard_of(t: pa.Table) -> Shard:
        return Shard(t["context"].to_pylist(), t["owner"].to_numpy(), length)

    def runs(t: pa.Table) -> pa.Table:
        s = shard_of(t)
        text = [x.tobytes() for x in s.strings()]
        return pa.table({"anchor": pa.array([t["anchor"][0].as_py()] * len(text), pa.int64()), "shard": pa.array([t["shard"][0].as_py()] * len(text), pa.int64()), "string": pa.array(text, pa.binary()), "low": pa.array(s.low, pa.int64())})

    def finish(t: pa.Table, lower: pa.Table) -> pa.Table:
        if not t.num_rows:
            return pa.table({k: pa.array([], pa.int64()) for k in ("anchor", "ctx", "owner", "hi", "below", "whole")})
        s = shard_of(t)
        if lower.num_rows:
            own = as_keys(s.strings())
            want = as_keys(np.frombuffer(b"".join(lower["string"].to_pylist()), np.uint8).reshape(lower.num_rows, length))
            at = np.searchsorted(own, want)
            s.low[at] = np.minimum(s.low[at], lower["least"].to_numpy())
        cols = [t[k].combine_chunks() for k in ("anchor", "ctx", "owner", "hi", "context")]
        return pa.Table.from_batches([verdict_rows(cols, s.masks(), length)])

    strings = materialize(rows.groupBy("anchor", "shard").applyInArrow(runs, "anchor long, shard long, string binary, low long"), "sa-strings")
    least = strings.groupBy("anchor", "string").agg(F.min("low").alias("least"), F.max("low").alias("most")).where("least < most")
    lower = materialize(strings.join(least, ["anchor", "string"]).where("least < low").select("anchor", "shard", "string", "least"), "sa-lower")
    out = materialize(rows.groupBy("anchor", "shard").cogroup(lower.groupBy("anchor", "shard")).applyInArrow(finish, JUDGED), "sa-large")
    release(strings, lower)
    return out


def judge(contexts: DataFrame, parts: int, length: int) -> DataFrame:
    """Verdicts over distinct contexts (anchor, ctx, owner, hi, context)."""
    large = materialize(contexts.groupBy("anchor").agg(F.sum(F.length("context")).alias("n")).where(F.col("n") > SHARD), "sa-large-anchors")
    none = large.isEmpty()
    plain = contexts if none else contexts.join(large.select("anchor"), "anchor", "left_anti")
    plain = plain.select("anchor", "ctx", "owner", "hi", "context").repartition(parts, "anchor").sortWithinPartitions("anchor").mapInArrow(judge_sorted(length), JUDGED)
    if not none:
        dealt = contexts.join(large, "anchor").withColumn("shard", F.pmod(F.xxhash64("ctx"), F.ceil(F.col("n") / SHARD)))
        plain = plain.unionByName(judge_large(materialize(dealt.drop("n"), "sa-dealt"), length))
    return materialize(plain, "sa-judged")


def strip_marked(length: int):
    """What is left of rows (doc_id, text, sha, marks)."""
    steps = np.arange(length - gram_bytes(length) + 1)

    def run(batches):
        for b in batches:
            out = []
            for t, m in zip(b.column(1), b.column(3), strict=True):
                raw = t.as_py().encode()
                places = m.values.field(0)
                sizes = places.value_lengths().to_numpy()
                at = places.flatten().to_numpy()
                bits = np.repeat(m.values.field(1).to_numpy(), sizes)
                turn = np.zeros(len(raw) + 1, np.int64)
                for i in range(0, len(at), 1 << 14):
                    on = (bits[i : i + (1 << 14), None] >> steps) & 1 == 1
                    p = (at[i : i + (1 << 14), None] + steps)[on]
                    turn += np.bincount(p, minlength=len(turn)) - np.bincount(p + length, minlength=len(turn))
                gone = np.cumsum(turn)[:-1] > 0
                edge = np.diff(np.concatenate([[0], gone.astype(np.int8), [0]]))
                a, z = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
                kept = np.frombuffer(raw, np.uint8)[~gone].tobytes()
                out.append((int(gone.sum()), len(a), hashlib.sha256(kept).hexdigest(), [{"start": int(x), "end": int(y)} for x, y in zip(a, z, strict=True)]))
            cols = list(zip(*out, strict=True)) if out else [()] * 4
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.string()), pa.array(cols[3], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))], names=["doc_id", "sha", "n_removed", "n_spans", "kept_sha256", "spans"])

    return run


def find_repeats(docs: DataFrame, length: int = 50) -> tuple[DataFrame, DataFrame]:
    """(rows, repeats): repeats has (doc_id, sha, n_removed, n_spans, kept_sha256, spans) of first documents that lose bytes."""
    spark = docs.sparkSession
    rows, firsts = distinct_texts(docs, length)
    # the distinct texts, bucketed by document: later joins by doc_id do not move texts again
    sizes = rows.agg(F.sum("n_bytes").alias("n")).first()
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), int((sizes.n or 0) // (64 << 20)))
    path = scratch(spark, "sa-texts")
    name = "t_" + path.rpartition("-")[2]
    hashed = docs.where("doc_id is not null and text is not null").select("doc_id", "text", F.unhex(F.sha2("text", 256)).alias("sha"))
    # joined by doc_id alone, so that the one exchange of texts serves the join and the buckets
    wanted = firsts.groupBy("doc_id").agg(F.collect_set("sha").alias("wanted"))
    kept = hashed.repartition(parts, "doc_id").join(wanted.repartition(parts, "doc_id"), "doc_id").where(F.array_contains("wanted", F.col("sha"))).drop("wanted")
    try:
        with writing(spark):
            kept.write.option("compression", "zstd").option("path", path).bucketBy(parts, "doc_id").sortBy("doc_id").saveAsTable(name)
        return rows, repeats_of(spark.table(name), parts, length)
    finally:
        spark.sql(f"drop table if exists {name}")
        gone = spark.range(0)
        gone._scratch = path
        release(gone)


def repeats_of(texts: DataFrame, parts: int, length: int) -> DataFrame:
    """(doc_id, sha, n_removed, n_spans, kept_sha256, spans) of the distinct texts (doc_id, text, sha) that lose bytes."""
    found = texts.select("doc_id", "text").mapInArrow(find_anchors(length), "anchor long, doc_id long")
    shared = materialize(found.groupBy("anchor").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).where("lo < hi").select("anchor"), "sa-shared")
    reply = materialize(found.join(shared.hint("shuffle_hash"), "anchor", "left_semi").groupBy("doc_id").agg(F.collect_list("anchor").alias("anchors")), "sa-reply")
    joined = texts.join(reply, "doc_id").select("doc_id", "text", F.xxhash64("text").alias("sid"), "anchors")
    places = materialize(joined.mapInArrow(cut_contexts(length), "anchor long, ctx long, doc_id long, sid long, at array<long>, context binary"), "sa-places")
    release(shared, reply)
    # each distinct context once, with the first and the last document that have it
    contexts = materialize(places.groupBy("anchor", "ctx", "context").agg(F.min("doc_id").alias("owner"), F.max("doc_id").alias("hi")), "sa-contexts")
    judged = judge(contexts, parts, length)
    release(contexts)
    mask = F.when(F.col("doc_id") > F.col("owner"), F.col("whole")).otherwise(F.col("below"))
    marks = places.select("anchor", "ctx", "doc_id", "sid", "at").join(judged, ["anchor", "ctx"]).select("doc_id", "sid", "at", mask.alias("mask")).where("mask <> 0")
    spans = materialize(marks.groupBy("doc_id", "sid").agg(F.collect_list(F.struct("at", "mask")).alias("marks")), "sa-marks")
    release(places, judged)
    own = texts.withColumn("sid", F.xxhash64("text")).join(spans, ["doc_id", "sid"]).select("doc_id", "text", "sha", "marks")
    repeats = materialize(own.mapInArrow(strip_marked(length), "doc_id long, sha binary, n_removed long, n_spans long, kept_sha256 string, spans array<struct<start:long,end:long>>"), "sa-repeats")
    release(spans)
    return repeats


def remove_repeats(docs: DataFrame, length: int = 50) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256) of every row."""
    rows, repeats = find_repeats(docs, length)
    firsts = rows.where((F.col("n_bytes") >= length) & F.col("doc_id").isNotNull()).groupBy("sha").agg(F.min("doc_id").alias("first"))
    copies = rows.join(firsts, "sha", "left")
    found = repeats.select("doc_id", "sha", "n_removed", "n_spans", "kept_sha256").distinct()
    out = copies.join(found, ["doc_id", "sha"], "left")
    copy = F.col("doc_id") > F.col("first")
    return out.select(
        "doc_id",
        "n_bytes",
        F.when(copy, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0))).cast("long").alias("n_removed"),
        F.when(copy, F.lit(1)).otherwise(F.coalesce("n_spans", F.lit(0))).cast("long").alias("n_spans"),
        F.when(copy, F.sha2(F.lit(""), 256)).otherwise(F.coalesce("kept_sha256", F.lower(F.hex("sha")))).alias("kept_sha256"),
    )


def op3_suffix_dedup(spark, sf_dir) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents", "doc_id", "text"))


OP3_SQL = """
with d as (select doc_id, hex(encode(coalesce(text, ''))) as hx, strlen(coalesce(text, '')) as n from documents),
w as (select doc_id, p, substring(hx, 2 * p + 1, 100) as win from (select doc_id, hx, unnest(range(0, n - 49)) as p from d where n >= 50)),
lo as (select win, min(doc_id) as first from w group by win),
hit as (select w.doc_id, w.p from w join lo using (win) where lo.first < w.doc_id),
step as (select doc_id, p, case when p <= lag(p) over (partition by doc_id order by p) + 50 then 0 else 1 end as fresh from hit),
isle as (select doc_id, p, sum(fresh) over (partition by doc_id order by p) as k from step),
span as (select doc_id, k, min(p) as a, max(p) + 50 as z from isle group by doc_id, k),
gap as (select s.doc_id, s.a, s.z, coalesce(lag(s.z) over (partition by s.doc_id order by s.a), 0) as from_ from span s),
agg as (select g.doc_id, sum(g.z - g.a)::bigint as n_removed, count(*) as n_spans,
  string_agg(substring(d.hx, 2 * from_ + 1, 2 * (a - from_)), '' order by a) || any_value(substring(d.hx, 2 * last.z + 1)) as kept
  from gap g join d using (doc_id) join (select doc_id, max(z) as z from span group by doc_id) last using (doc_id) group by g.doc_id)
select d.doc_id, d.n::bigint as n_bytes, coalesce(n_removed, 0)::bigint as n_removed, coalesce(n_spans, 0)::bigint as n_spans,
  sha256(unhex(case when agg.doc_id is null then d.hx else agg.kept end)) as kept_sha256
from d left join agg using (doc_id)
"""
