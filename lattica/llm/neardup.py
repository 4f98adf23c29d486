"""Near-duplicate classes by ProbMinHash, banding and verification.

A text is the set of its shingles of five lower-case words (runs of characters
other than ASCII white space; a shorter text is one shingle). Each shingle is a
Poisson process whose rate is its weight and whose arrivals and registers derive
from its hash; a register keeps the shingle that arrives first. Two registers agree
with the probability Jaccard of the weighted sets. All weights are 1 here, so that
the registers estimate the very similarity that the links are tested for, however
often a passage is repeated. A shingle stops as soon as its next arrival is later
than every register.

Texts that agree on all registers of one of ``bands`` bands are candidates, and a
candidate is a link only if the exact Jaccard similarity of the shingle sets is at
least ``threshold``. Classes are the connected components of the links.

No bucket is expanded into pairs: in each round a bucket that still holds several
components offers one pivot (first the text that meets most others), and each text is
compared with its best few offers. After the rounds, what is still apart within a bucket
is compared in blocks of shingle sets, each against each and exactly; of its links a block
gives only those that join components that it has not joined yet.

Defined results: exact copies (equal word sequences) are one node; null and empty
texts and texts without words are never near-duplicates (each row its own class);
a text held only by rows with a null doc_id has no near links (its copies are one
class); class_id is the smallest non-null doc_id of the class; extra columns are ignored.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import PrefixHash, materialize, mix64, padded, release, slices, table, words
from .components import components

WIDTH = 5
REGISTERS, BANDS = 192, 32
#: Pivots that a node is compared with in one round.
OFFERS = 3
#: Members of a bucket that are compared as one matrix.
BLOCK = 128
#: Bytes of shingles that a block holds on average at most.
BLOCK_BYTES = 1 << 20
STEP = np.uint64(0xA0761D6478BD642F)
PLACE = [np.uint64(x) for x in (0x8EBC6AF09C88C6E3, 0x589965CC75374CC3, 0x1D8E4E27C47D124F, 0xEB44ACCAB455D165, 0x9FB21C651E98DF25)]


def shingles(tools: PrefixHash, column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Text index and hash of every shingle; word hashes; word offsets of the texts."""
    data, off = padded(column, True)
    start, end = words(data)
    h = tools.ranges(tools.sums(data), start, end)
    cut = np.searchsorted(start, off)
    size = np.diff(cut)
    n = len(h)
    doc = np.repeat(np.arange(len(size)), size)
    left = np.repeat(cut[1:], size) - np.arange(n)  # words from here to the end of the text
    total = np.zeros(n, np.uint64)
    for i, c in enumerate(PLACE):
        part = np.zeros(n, np.uint64)
        part[: max(0, n - i)] = h[i:] * c
        total += np.where(left > i, part, np.uint64(0))
    first = left == np.repeat(size, size)
    keep = (left >= WIDTH) | (first & (left < WIDTH))
    return doc[keep], mix64(total[keep]), h, cut


def weighted(doc: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (text, shingle) in order, and their counts."""
    order = np.lexsort((h, doc))
    doc, h = doc[order], h[order]
    new = np.ones(len(h), bool)
    new[1:] = (doc[1:] != doc[:-1]) | (h[1:] != h[:-1])
    at = np.flatnonzero(new)
    return doc[at], h[at], np.diff(np.append(at, len(h)))


def signatures(n: int, doc: np.ndarray, h: np.ndarray, count: np.ndarray, m: int = REGISTERS) -> np.ndarray:
    """The n x m register contents (shingle hashes) of n texts."""
    time = np.full(n * m, np.inf)
    held = np.zeros(n * m, np.uint64)
    rate = 1.0 + np.log(count)
    arrival, salt = np.zeros(len(h)), np.uint64(0)
    doc, h = doc.copy(), h.copy()
    while len(h):
        with np.errstate(over="ignore"):
            salt += STEP
            draw = mix64(h + salt)
            spot = doc * m + (mix64(draw + STEP) % np.uint64(m)).astype(np.int64)
        arrival -= np.log(((draw >> np.uint64(11)).astype(float) + 0.5) * 2.0**-53) / rate
        np.minimum.at(time, spot, arrival)
        won = arrival == time[spot]
        held[spot[won]] = h[won]
        active = arrival < time.reshape(n, m).max(1)[doc]
        doc, h, rate, arrival = doc[active], h[active], rate[active], arrival[active]
    return held.reshape(n, m)


def band_keys(registers: np.ndarray, bands: int = BANDS) -> np.ndarray:
    rows = registers.shape[1] // bands
    out = np.tile(np.arange(1, bands + 1, dtype=np.uint64) * STEP, (len(registers), 1))
    for i in range(rows):
        out = mix64(out + registers[:, i::rows][:, :bands] * PLACE[i % len(PLACE)])
    return out


def sketch(docs: DataFrame) -> DataFrame:
    """(doc_id, text_key, node, bands): node identifies the word sequence (null without words), text_key is xxhash64 of the text."""

    def run(batches):
        tools = PrefixHash()
        for whole in batches:
            for b in slices(whole, "text"):
                n = b.num_rows
                doc, h, word, cut = shingles(tools, b.column(1))
                doc, h, count = weighted(doc, h)
                keys = band_keys(signatures(n, doc, h, np.ones(len(count)))).astype(np.int64)
                nodes, bands = [], []
                for i in range(n):
                    own = word[cut[i] : cut[i + 1]]
                    nodes.append(hashlib.blake2b(own.tobytes(), digest_size=16).digest() if len(own) else None)
                    bands.append(keys[i] if len(own) else None)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(nodes, pa.binary()), pa.array(bands, pa.list_(pa.int64()))], names=["doc_id", "text_key", "node", "bands"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text", F.xxhash64("text").alias("text_key")).mapInArrow(run, f"doc_id {kind}, text_key long, node binary, bands array<long>")


def shingle_sets(texts: DataFrame, own_only: bool = False) -> DataFrame:
    """(node, shingles): the packed sorted distinct shingle hashes of rows (node, text); own_only leaves out texts whose words do not give the node."""

    def run(batches):
        tools = PrefixHash()
        for whole in batches:
            for b in slices(whole, "text"):
                doc, h, word, cut = shingles(tools, b.column(1))
                doc, h, _ = weighted(doc, h)
                edge = np.searchsorted(doc, np.arange(b.num_rows + 1))
                own = [not own_only or hashlib.blake2b(word[a:z].tobytes(), digest_size=16).digest() == n for a, z, n in zip(cut[:-1], cut[1:], b.column(0).to_pylist(), strict=True)]
                packed = [h[a:z].tobytes() for a, z in zip(edge[:-1], edge[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(packed, pa.binary())], names=["node", "shingles"]).filter(pa.array(own, pa.bool_()))

    return texts.select("node", "text").mapInArrow(run, "node binary, shingles binary")


def block_links(x: tuple[list, list, list], y: tuple[list, list, list], threshold: float) -> list[tuple[bytes, bytes]]:
    """Links that join the components of two blocks (nodes, components, packed shingles), exact and without cycles."""
    sets = [np.frombuffer(v, np.uint64) for v in (*x[2], *y[2])]
    sizes = np.array([len(v) for v in sets])
    code = np.unique(np.concatenate(sets), return_inverse=True)[1] if len(sets) else np.empty(0, np.int64)
    at = np.concatenate([[0], np.cumsum(sizes)])
    mark = np.zeros(len(code) + 1, bool)
    k = len(x[0])
    theirs, n = code[at[k] :], sizes[k:]
    starts = at[k:-1] - at[k]
    top: dict[bytes, bytes] = {}

    def root(c):
        while c in top:
            c = top[c]
        return c

    out = []
    for i in range(k):
        # sets of such different sizes cannot be as similar
        fits = np.flatnonzero(np.minimum(n, sizes[i]) / np.maximum(1, np.maximum(n, sizes[i])) >= threshold)
        mine = root(x[1][i])
        fits = [j for j in fits.tolist() if y[1][j] != x[1][i] and root(y[1][j]) != mine]
        if not fits:
            continue
        own = code[at[i] : at[i + 1]]
        mark[own] = True
        both = np.add.reduceat(mark[theirs], starts, dtype=np.int64)[fits]
        mark[own] = False
        for j in np.array(fits)[both / np.maximum(1, sizes[i] + n[fits] - both) >= threshold].tolist():
            r, q = root(x[1][i]), root(y[1][j])
            if r != q:
                top[max(r, q)] = min(r, q)
                out.append((min(x[0][i], y[0][j]), max(x[0][i], y[0][j])))
    return out


def compared(left: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    """(a, b): links between components that share a bucket; every pair of a bucket is compared exactly.

    Members of a bucket are packed into blocks; blocks meet blocks and the comparison is a
    matrix inside, so a large bucket makes rows by the square of its blocks, not of its members.
    """
    rows = materialize(left.join(sets.select("node", "shingles"), "node"), "nd-rows")
    # written: Spark then knows its size, and deals a hot bucket anew if it has to join by bucket
    sizes = materialize(rows.groupBy("bucket").agg(F.greatest(F.count("*") / BLOCK, F.sum(F.length("shingles")) / BLOCK_BYTES).alias("n")), "nd-sizes")
    block = F.pmod(F.xxhash64("node"), F.ceil("n")).alias("block")
    packed = rows.join(sizes, "bucket").groupBy("bucket", block).agg(F.collect_list(F.struct("node", "comp", "shingles")).alias("x"), F.min("comp").alias("lo"), F.max("comp").alias("hi"))
    packed = materialize(packed, "nd-blocks")
    other = packed.select("bucket", F.col("block").alias("block2"), F.col("x").alias("y"), F.col("lo").alias("lo2"), F.col("hi").alias("hi2"))
    # two blocks of one and the same component have nothing to compare
    met = packed.join(other, "bucket").where("block <= block2 and not (lo = hi and lo2 = hi2 and lo = lo2)").select("x", "y")

    def part(column, i):
        a, z = column.offsets[i].as_py(), column.offsets[i + 1].as_py()
        members = column.values.slice(a, z - a)
        return tuple(members.field(k).to_pylist() for k in range(3))

    def run(batches):
        for b in batches:
            rows = sorted({r for i in range(b.num_rows) for r in block_links(part(b.column(0), i), part(b.column(1), i), threshold)})
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.binary()), pa.array([r[1] for r in rows], pa.binary())], names=["a", "b"])

    return met.mapInArrow(run, "a binary, b binary")


def verified(pairs: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    """The pairs (a, b) whose shingle sets have at least the similarity, with it."""

    def run(batches):
        for b in batches:
            sims = []
            for x, y in zip(b.column(2), b.column(3), strict=True):
                x, y = np.frombuffer(x.as_py(), np.uint64), np.frombuffer(y.as_py(), np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                sims.append(both / max(1, len(x) + len(y) - both))
            keep = pa.array([s >= threshold for s in sims], pa.bool_())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(sims, pa.float64())], names=["a", "b", "similarity"]).filter(keep)

    left = pairs.join(sets.select(F.col("node").alias("a"), F.col("shingles").alias("x")), "a")
    full = left.join(sets.select(F.col("node").alias("b"), F.col("shingles").alias("y")), "b")
    return full.select("a", "b", "x", "y").mapInArrow(run, "a binary, b binary, similarity double")


def node_classes(docs: DataFrame, sketched: DataFrame, threshold: float = 0.8, rounds: int = 2) -> DataFrame:
    """(node, comp) of the nodes that have a link."""
    one = materialize(sketched.where("node is not null").groupBy("node").agg(F.min("bands").alias("bands"), F.min("doc_id").alias("doc_id")), "nd-nodes")
    spread = one.select("node", F.explode("bands").alias("bucket"))
    shared = materialize(spread.groupBy("bucket").agg(F.min("node").alias("lo"), F.max("node").alias("hi"), F.count("*").alias("size")).where("lo <> hi").select("bucket", "size"), "nd-shared")
    spots = materialize(spread.join(shared, "bucket"), "nd-spots")
    # how many others a node meets: in a group of edited copies the least edited one meets most
    meets = spots.groupBy("node").agg(F.sum("size").alias("meets"))
    members = materialize(spots.join(meets, "node").select("bucket", "node", "meets"), "nd-members")
    wanted = members.select("node").distinct()
    source = one.select("node", "doc_id").join(wanted, "node", "left_semi")
    texts = docs.select("doc_id", "text").where("doc_id is not null").join(source, "doc_id")
    # ids may repeat with other texts: the set of the right text is the one whose words give the node
    sets = materialize(shingle_sets(texts, own_only=True), "nd-sets")
    comps, seen, last = None, [], False
    for r in range(rounds + 1):
        state = members.withColumn("comp", F.col("node")) if comps is None else members.join(comps, "node", "left").select("bucket", "node", "meets", F.coalesce("comp", "node").alias("comp"))
        last = last or r == rounds
        if not last:  # a bucket that holds several components offers one pivot; a node is compared with its few best offers
            rank = F.struct((F.xxhash64(F.lit(r), "node") if r else -F.col("meets")).alias("h"), "node", "comp")
            split = materialize(state.groupBy("bucket").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi"), F.min(rank).alias("p")).where("lo <> hi").select("bucket", "p"), "nd-split")
            offers = state.join(split, "bucket").where(F.col("comp") != F.col("p.comp")).select("node", "p").distinct()
            best = offers.groupBy("node").agg(F.slice(F.sort_array(F.collect_list("p")), 1, OFFERS).alias("ps"))  # at most one offer a band
            pairs = best.select("node", F.explode("ps").alias("p")).select(F.least("node", "p.node").alias("a"), F.greatest("node", "p.node").alias("b"))
        else:  # what is still apart in a bucket, each against each
            split = materialize(state.groupBy("bucket").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("bucket"), "nd-split")
            left = materialize(state.join(split, "bucket"), "nd-apart")
            found = materialize(compared(left.select("bucket", "node", "comp"), sets, threshold).distinct(), "nd-links")
        if not last:
            pairs = pairs.distinct()
            for old in seen:
                pairs = pairs.join(old, ["a", "b"], "left_anti")
            pairs = materialize(pairs, "nd-pairs")
            found = materialize(verified(pairs, sets, threshold).select("a", "b"), "nd-links")
            seen.append(pairs)
        release(split)
        none = found.isEmpty()
        if not none:
            comps = joined_up(comps, found)
        if last:
            break
        last = none  # pivots merge no more
    release(one, shared, spots, members, sets, *seen)
    return comps


def joined_up(comps: DataFrame | None, links: DataFrame) -> DataFrame:
    """The components after further links: components of components, then one join."""
    if comps is None:
        return components(links)
    ends = links
    for k in ("a", "b"):
        ends = ends.join(comps.select(F.col("node").alias(k), F.col("comp").alias(f"c_{k}")), k, "left").withColumn(k, F.coalesce(f"c_{k}", k)).drop(f"c_{k}")
    upper = components(ends.where("a <> b").distinct())
    up = upper.select(F.col("node").alias("comp"), F.col("comp").alias("top"))
    old = comps.join(up, "comp", "left").select("node", F.coalesce("top", "comp").alias("comp"))
    fresh = upper.join(comps.select("node"), "node", "left_anti")  # nodes that had no link before
    return materialize(old.unionByName(fresh), "nd-comps")


def classes(docs: DataFrame, threshold: float = 0.8) -> DataFrame:
    """(doc_id, text_key, class_id, is_first) of every row of docs (doc_id, text)."""
    sketched = materialize(sketch(docs), "nd-sketch")
    comps = node_classes(docs, sketched, threshold)
    rows = sketched.select("doc_id", "text_key", "node")
    labelled = rows.withColumn("comp", F.col("node")) if comps is None else rows.join(comps, "node", "left").select("doc_id", "text_key", F.coalesce("comp", "node").alias("comp"))
    least = materialize(labelled.where("comp is not null").groupBy("comp").agg(F.min("doc_id").alias("least")), "nd-least")
    out = labelled.join(least, "comp", "left").select("doc_id", "text_key", F.coalesce("least", "doc_id").alias("class_id"))
    return out.withColumn("is_first", F.coalesce(F.col("doc_id") == F.col("class_id"), F.col("class_id").isNull()))


def keep_first(docs: DataFrame, threshold: float = 0.8) -> DataFrame:
    """The documents without the later members of near-duplicate classes; of equal rows one stays."""
    first = materialize(classes(docs, threshold).where("is_first").select("doc_id", "text_key"), "nd-first")
    twice = first.where("doc_id is not null").groupBy("doc_id", "text_key").count().where("count > 1")
    keyed = docs.withColumn("text_key", F.xxhash64("text"))
    same = keyed.doc_id.eqNullSafe(first.doc_id) & (keyed.text_key == first.text_key)
    kept = keyed.join(first, same, "left_semi")
    return (kept if twice.isEmpty() else kept.dropDuplicates(["doc_id", "text_key"])).drop("text_key")


def op2_prob_minhash(spark, sf_dir) -> DataFrame:
    return classes(table(spark, sf_dir, "documents", "doc_id", "text")).drop("text_key")
