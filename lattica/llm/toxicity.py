"""Toxicity by a factorization machine over hashed terms.

A text is the set of its lower-case words and word stems, hashed to ``BITS`` bits. The
score is the logistic of bias + linear weights + all pairwise interactions (the inner
products of the terms' factors), so an insult counts for more beside a mention of a
group than the sum of both. A term enters the model if the labels differ by it alone
(its document frequencies by ``least_z`` standard errors) or by it beside another term
(their joint frequencies by ``pair_z``, and clearly more than by either alone), so words
that tell something only together are kept. Pairs are sought among the ``pair_terms``
most frequent terms.

The model is fitted on the driver on at most ``sample`` labelled rows (the smallest
hashes of doc_id); scoring reads whole texts and is one pass without a shuffle.

Defined results: null and empty texts have no terms and score as the bias alone;
repeated words count once; rows with null labels are not learned from; a sample
without both labels scores every text as the share of label 1; repeated labels of a
document count once, the largest; columns besides doc_id and text are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import NOT_WORD, PrefixHash, crc_mod, padded, plus, slices, table, words


#: Byte lengths of the stems that are terms beside the whole words.
STEMS = (6, 7)
#: Bits of a term's hash.
BITS = 22


@dataclass
class Machine:
    bias: float = 0.0
    terms: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int32))
    linear: np.ndarray = field(default_factory=lambda: np.zeros(0))
    factors: np.ndarray = field(default_factory=lambda: np.zeros((0, 1)))

    def scores(self, n: int, doc: np.ndarray, term: np.ndarray) -> np.ndarray:
        """Probabilities of n texts from their distinct (text, term index) pairs."""
        z = np.full(n, self.bias) + np.bincount(doc, self.linear[term], n)
        for v in self.factors.T:
            z += (np.bincount(doc, v[term], n) ** 2 - np.bincount(doc, v[term] ** 2, n)) / 2
        return 1 / (1 + np.exp(-np.clip(z, -60, 60)))


def term_sets(tools: PrefixHash, batch: pa.RecordBatch, text: str):
    """Text index and hash of every word of a batch (with repeats), and of the stems (first STEMS bytes) of longer ones."""
    data, off = padded(batch.column(batch.schema.get_field_index(text)), True)
    start, end = words(data, NOT_WORD)
    sums, doc = tools.sums(data), np.searchsorted(off, start, "right") - 1
    hashes, docs = [tools.ranges(sums, start, end)], [doc]
    for n in STEMS:
        long = np.flatnonzero(end - start > n)
        hashes.append(tools.ranges(sums, start[long], start[long] + n) ^ np.uint64(n))
        docs.append(doc[long])
    doc = np.concatenate(docs)
    order = np.argsort(doc, kind="stable")
    return doc[order], (np.concatenate(hashes)[order] >> np.uint64(64 - BITS)).astype(np.int32)


def labelled_terms(rows: DataFrame) -> list:
    """(label, packed distinct terms) of rows (doc_id, text, label)."""

    def run(batches):
        tools = PrefixHash()
        for whole in batches:
            for b in slices(whole, "text"):
                doc, h = term_sets(tools, b, "text")
                cut = np.searchsorted(doc, np.arange(b.num_rows + 1))
                packed = [np.unique(h[a:z]).tobytes() for a, z in zip(cut[:-1], cut[1:], strict=True)]
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), pa.array(packed, pa.binary())], names=["doc_id", "label", "terms"])

    kind = rows.schema["doc_id"].dataType.simpleString()
    got = rows.select("doc_id", "text", F.col("label").cast("int").alias("label")).mapInArrow(run, f"doc_id {kind}, label int, terms binary").collect()
    return sorted(((r.doc_id, r.label, r.terms) for r in got), key=lambda r: (r[0] is None, r[0], r[1]))


def fit(rows: DataFrame, sample: int = 8000, **how) -> Machine:
    """Fit on at most `sample` rows (doc_id, text, label 0 or 1)."""
    got = labelled_terms(rows.where("label is not null").orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample))
    return train(np.array([x[1] for x in got], float), [np.frombuffer(x[2], np.int32) for x in got], **how)


def apart(one: np.ndarray, all_: np.ndarray, n1: float, n: int) -> np.ndarray:
    """Standard errors between the labels' shares of texts, of which `one` have label 1 and `all_` any."""
    p = all_ / n
    return (one / n1 - (all_ - one) / (n - n1)) / np.sqrt(np.maximum(p * (1 - p), 1e-12) * (1 / n1 + 1 / (n - n1)))


def telling(y: np.ndarray, every: np.ndarray, owner: np.ndarray, least_z: float, pair_z: float, pair_terms: int, least_texts: int) -> np.ndarray:
    """The terms by which the labels differ, alone or in pairs."""
    n1, n = y.sum(), len(y)
    df = np.bincount(every, minlength=1 << BITS)
    alone = apart(np.bincount(every, y[owner], 1 << BITS), df, n1, n)
    keep = (np.abs(alone) >= least_z) & (df >= least_texts)
    often = np.flatnonzero(df >= least_texts)
    often = often[np.argsort(-df[often], kind="stable")[:pair_terms]]
    place = np.full(1 << BITS, -1, np.int32)
    place[often] = np.arange(len(often))
    joint = np.zeros((2, len(often), len(often)), np.float32)
    for at in range(0, n, 512):  # joint frequencies by label, some texts at a time
        a, z = np.searchsorted(owner, [at, at + 512])
        here = place[every[a:z]]
        has = np.zeros((min(512, n - at), len(often)), np.float32)
        has[owner[a:z][here >= 0] - at, here[here >= 0]] = 1
        for label in (0, 1):
            own = has[y[at : at + 512] == label]
            joint[label] += own.T @ own
    both = np.abs(apart(joint[1], joint[0] + joint[1], n1, n))
    single = np.abs(alone[often])
    both[(joint[0] + joint[1] < least_texts) | (both < pair_z) | (both < np.maximum(single[:, None], single) + least_z)] = 0
    keep[often[both.any(1)]] = True
    return np.flatnonzero(keep)


def train(y: np.ndarray, sets: list[np.ndarray], least_z: float = 3.0, pair_z: float = 6.0, pair_terms: int = 1024, least_texts: int = 3, rank: int = 6, epochs: int = 12, batch: int = 128, rate: float = 0.05, shrink: float = 2e-4, seed: int = 7) -> Machine:
    """Adaptive gradient steps on the logistic loss of labels y over distinct terms."""
    if not len(y) or y.min() == y.max():
        p = min(max(y.mean() if len(y) else 0.0, 1e-6), 1 - 1e-6)
        return Machine(float(np.log(p / (1 - p))))
    n1, n = y.sum(), len(y)
    every = np.concatenate(sets)
    owner = np.repeat(np.arange(n, dtype=np.int32), [len(s) for s in sets])
    terms = telling(y, every, owner, least_z, pair_z, pair_terms, least_texts)
    place = np.full(1 << BITS, -1, np.int32)
    place[terms] = np.arange(len(terms))
    index = place[every]
    use = index >= 0
    owner, index = owner[use], index[use]
    k = len(terms)
    rng = np.random.default_rng(seed)
    m = Machine(float(np.log(n1 / (n - n1))), terms.astype(np.int32), np.zeros(k), rng.normal(0, 0.05, (k, rank)))
    start = np.searchsorted(owner, np.arange(n + 1))
    theta = [np.array([m.bias]), m.linear, m.factors]
    first, second, t = [np.zeros_like(x) for x in theta], [np.zeros_like(x) for x in theta], 0
    for _ in range(epochs):
        order = rng.permutation(n)
        for at in range(0, n, batch):
            pick = order[at : at + batch]
            size = start[pick + 1] - start[pick]
            doc = np.repeat(np.arange(len(pick)), size)
            pos = np.repeat(start[pick] - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum())
            term = index[pos]
            sums = np.stack([np.bincount(doc, m.factors[term, f], len(pick)) for f in range(rank)], 1)
            gap = m.scores(len(pick), doc, term) - y[pick]
            g = gap[doc] / len(pick)
            inner = g[:, None] * (sums[doc] - m.factors[term])
            grads = [np.array([gap.mean()]), np.bincount(term, g, k) + shrink * m.linear, np.stack([np.bincount(term, inner[:, f], k) for f in range(rank)], 1) + shrink * m.factors]
            t += 1
            for x, d, a, b in zip(theta, grads, first, second, strict=True):
                a += 0.1 * (d - a)
                b += 0.001 * (d * d - b)
                x -= rate * (a / (1 - 0.9**t)) / (np.sqrt(b / (1 - 0.999**t)) + 1e-8)
            m.bias = float(theta[0][0])
    return m


def score(docs: DataFrame, model: Machine) -> DataFrame:
    """The documents with their score, one pass."""
    names = [c for c in docs.columns if c != "score"]
    at = names.index("text")

    def run(batches):
        tools = PrefixHash()
        for whole in batches:
            for b in slices(whole, "text"):
                doc, h = term_sets(tools, b, "text")
                i = np.searchsorted(model.terms, h)
                hit = np.flatnonzero(model.terms[np.minimum(i, len(model.terms) - 1)] == h) if len(model.terms) else np.zeros(0, int)
                pair = np.unique(doc[hit] * np.int64(max(1, len(model.terms))) + i[hit])
                d, t = np.divmod(pair, max(1, len(model.terms)))
                p = model.scores(b.num_rows, d, t)
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(p)], names=[*names, "score"])

    docs = docs.select(*names)
    assert at >= 0
    return docs.mapInArrow(run, plus(docs.schema, score="double"))


def learn(docs: DataFrame, labels: DataFrame) -> Machine:
    """A machine from the labels outside the held-out fifth."""
    marks = labels.where((crc_mod(F.col("doc_id"), 5) != 0) & F.col("toxic").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("label"))
    marks = marks.orderBy(F.xxhash64("doc_id"), "doc_id").limit(8000)
    return fit(docs.select("doc_id", "text").join(F.broadcast(marks), "doc_id"))  # at most 8000 short rows


def op8_toxicity(spark, sf_dir) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    model = learn(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    out = score(docs, model)
    return out.select("doc_id", (crc_mod(F.col("doc_id"), 5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
