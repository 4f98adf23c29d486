"""Benchmark decontamination by spaced seeds, with DataFrame functions only.

Texts and items are sequences of lower-case words (runs of letters and digits). A
seed is a fixed mask over consecutive positions: words at ignored places may
differ. Hashes of all masked positions of the items are joined to those of all
documents; every hit fixes an alignment (document position minus item position),
which is then verified word by word over the whole item.

A document is contaminated by an item if some window of min(13, item length) item
words agrees with the aligned document words in all but ``allowed`` places: 2 for
windows of 10 to 13 words, 1 for 8 or 9, 0 below. The masks find every such
alignment (checked by enumeration in the tests).

Verdicts depend on the text alone, so they are found once for each distinct text.
Defined results: null and empty texts are clean; items of fewer than 3 words are
not looked for; equal overlaps go to the smallest item id; repeated rows and ids
each get their verdict; extra columns of the documents pass through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, release, table

#: Positions that each mask reads.
MASKS = ((0, 3, 4, 6, 7), (0, 1, 2, 3, 6), (0, 1, 5, 6, 7))
WINDOW = 13
SHORT = range(3, 8)
MOST_SEEDS = 4_000_000


def allowed(window):
    return F.when(window >= 10, 2).when(window >= 8, 1).otherwise(0)


def tokens(text):
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda t: t != "")


def seeds(hashes, masks) -> list:
    """For each mask the array of its hash at every position (places past the end are skipped)."""

    def one(k, mask):
        return F.transform(hashes, lambda x, i: F.xxhash64(F.lit(k), x, *[F.get(hashes, i + p) for p in mask[1:]]))

    return [one(k, m) for k, m in masks]


def item_seeds(items: DataFrame) -> DataFrame:
    """(seed, item_id, place) of all items (item_id, words)."""
    long = items.where(F.size("words") >= 8)
    parts = []
    for k, m in enumerate(MASKS):
        h = F.transform("words", lambda t: F.xxhash64(t))
        parts.append(long.select("item_id", h.alias("h"), (F.size("words") - max(m)).alias("n")).select("item_id", "n", F.posexplode(seeds(F.col("h"), [(k, m)])[0]).alias("place", "seed")).where("place < n"))
    for n in SHORT:
        parts.append(items.where(F.size("words") == n).select("item_id", F.lit(1).alias("n"), F.lit(0).alias("place"), F.xxhash64(F.lit(len(MASKS) + n), *[F.xxhash64(F.get("words", F.lit(i))) for i in range(n)]).alias("seed")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.select("seed", "item_id", "place").distinct()


def verdicts(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(key, item_id, matched, overlap) of every contaminated distinct text; key is xxhash64 of the text."""
    items = materialize(benchmark.where("item_id is not null and text is not null").select("item_id", tokens(F.col("text")).alias("words")).where(F.size("words") >= SHORT[0]), "items")
    index = materialize(item_seeds(items), "item-seeds")
    short = [r[0] for r in items.where(F.size("words") < 8).select(F.size("words")).distinct().collect()]  # at most five lengths
    masks = [*enumerate(MASKS), *((len(MASKS) + n, tuple(range(n))) for n in sorted(short))]
    small = index.count() <= MOST_SEEDS
    probe = docs.select(F.xxhash64("text").alias("key"), F.transform(tokens(F.col("text")), lambda t: F.xxhash64(t)).alias("h")).where(F.size("h") >= SHORT[0])
    flat = probe.select("key", F.size("h").alias("n"), F.posexplode(F.flatten(F.array(*seeds(F.col("h"), masks)))).alias("at", "seed"))
    hits = flat.join(F.broadcast(index) if small else index, "seed").select("key", "item_id", (F.col("at") % F.col("n") - F.col("place")).alias("shift")).distinct()
    hits = materialize(hits, "seed-hits")
    texts = docs.select(F.xxhash64("text").alias("key"), "text").join(hits.select("key").distinct(), "key", "left_semi").groupBy("key").agg(F.first("text").alias("text"))
    words = texts.select("key", tokens(F.col("text")).alias("found"))
    pairs = hits.join(words, "key").join(F.broadcast(items) if small else items, "item_id")
    same = F.transform("words", lambda w, i: F.when((F.col("shift") + i >= 0) & (F.get("found", F.col("shift") + i) == w), 1).otherwise(0))
    window = F.least(F.lit(WINDOW), F.size("words"))
    runs = F.transform(F.sequence(F.lit(1), F.size("same") - window + 1), lambda s: F.aggregate(F.slice("same", s, window), F.lit(0), lambda a, x: a + x))
    judged = pairs.select("key", "item_id", "words", same.alias("same")).select("key", "item_id", F.size("words").alias("size"), window.alias("window"), F.aggregate("same", F.lit(0), lambda a, x: a + x).cast("long").alias("matched"), F.array_max(runs).alias("best"))
    bad = judged.where(F.col("best") >= F.col("window") - allowed(F.col("window"))).withColumn("overlap", F.col("matched") / F.col("size"))
    top = F.max(F.struct("overlap", (-F.col("item_id")).alias("order"), "item_id", "matched"))
    out = materialize(bad.groupBy("key").agg(top.alias("t")).select("key", "t.item_id", "t.matched", "t.overlap"), "verdicts")
    release(items, index, hits)
    return out


def judge(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents with contaminated, item_id, matched_words and overlap."""
    found = verdicts(docs, benchmark)
    named = found.select(F.col("key").alias("__key"), "item_id", F.col("matched").alias("matched_words"), "overlap")
    own = docs.drop("contaminated", "item_id", "matched_words", "overlap").withColumn("__key", F.xxhash64("text"))
    return own.join(named, "__key", "left").drop("__key").withColumn("contaminated", F.col("item_id").isNotNull())


def op10_decontaminate(spark, sf_dir) -> DataFrame:
    out = judge(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"))
    return out.select("doc_id", "contaminated", "item_id", F.coalesce("matched_words", F.lit(0)).cast("long").alias("matched_words"), F.coalesce("overlap", F.lit(0.0)).alias("overlap"))


OP10_SQL = r"""
with d as (select doc_id, list_filter(string_split_regex(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') as w from documents),
b as (select item_id, list_filter(string_split_regex(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') as w from benchmark),
bi as (select item_id, len(w) as size, least(13, len(w)) as win, unnest(w) as tok, unnest(range(len(w))) as j from b where len(w) >= 3),
di as (select doc_id, unnest(w) as tok, unnest(range(len(w))) as i from d),
al as (select doc_id, item_id, i - j as shift, any_value(size) as size, any_value(win) as win, list(j order by j) as js
  from di join bi using (tok) group by doc_id, item_id, i - j
  having count(*) >= any_value(win) - case when any_value(win) >= 10 then 2 when any_value(win) >= 8 then 1 else 0 end),
good as (select doc_id, item_id, len(js) as matched, len(js) / size as overlap from al
  where list_max(list_transform(js, lambda s: len(list_filter(js, lambda x: x >= s and x < s + win)))) >= win - case when win >= 10 then 2 when win >= 8 then 1 else 0 end),
top as (select doc_id, arg_max(struct_pack(i := item_id, m := matched, o := overlap), row(overlap, -item_id, matched)) as t from good group by doc_id)
select d.doc_id, t is not null as contaminated, t.i as item_id, coalesce(t.m, 0)::bigint as matched_words, coalesce(t.o, 0.0)::double as overlap
from d left join top using (doc_id)
"""
