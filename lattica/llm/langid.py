"""Language identification by compression.

Every language keeps a raw-content zstandard dictionary made of sample texts. A
text is cut into chunks (so that the dictionary counts for long texts too), each
chunk is compressed with every dictionary, and the language with the smallest
total wins. The margin between the two smallest totals, relative to the larger,
is the evidence; below ``margin`` the operator's ``accepted`` is false.

Training is fitted on a bounded sample of each language: the first ``2 * dict_bytes /
per_lang`` characters of at most ``per_lang`` labelled texts of ``LONG`` characters or more
(the smallest hashes of doc_id), and, as far as those leave room, at most ``FILL`` shorter
texts. A dictionary keeps ``dict_bytes`` bytes. Every language with a labelled text that
has a letter is learned, however short its texts are.

Defined results: null texts and texts without a letter are 'und' with score 0;
equal sizes go to the language first in order; one learned language wins every
text with a score from its own gain; without any labelled row all rows are 'und';
extra columns are ignored.
"""

from __future__ import annotations

import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import crc_mod, slices, table

#: Characters from which a text is preferred for training, and the most shorter ones that fill a dictionary up.
LONG, FILL = 200, 1024
LETTER = re.compile(r"[^\W\d_]")


def clean(text: str) -> str:
    """Lower case with everything but letters folded to single blanks: digits and symbols tell no language."""
    return re.sub(r"[\W\d_]+", " ", text.lower()).strip()


def fit(labelled: DataFrame, per_lang: int = 48, dict_bytes: int = 64 << 10) -> dict[str, bytes]:
    """Dictionaries by language from rows (doc_id, text, lang); the sample bound is per_lang texts of dict_bytes / per_lang * 2 characters."""
    piece = max(1, 2 * dict_bytes // per_lang)
    parts: dict[str, list[str]] = {}
    known = labelled.where("lang is not null and text is not null")
    rank = F.row_number().over(W.partitionBy("lang").orderBy(F.xxhash64("doc_id"), "doc_id", "text"))
    size = F.length("text")
    for few, wanted in ((per_lang, size >= LONG), (FILL, size < LONG)):
        rows = known.where(wanted).select("lang", "doc_id", F.substring("text", 1, piece).alias("text")).withColumn("r", rank).where(F.col("r") <= few)
        for x in sorted(rows.select("lang", "r", "text").collect()):  # at most languages * (per_lang * piece + FILL * LONG) characters
            own = parts.setdefault(x.lang, [])
            if sum(map(len, own)) < 2 * dict_bytes:
                own.append(clean(x.text))
    return {k: " ".join(t for t in v if t).encode()[-dict_bytes:] for k, v in sorted(parts.items())}


def predict(docs: DataFrame, model: dict[str, bytes], margin: float = 0.01, chunk: int = 16384) -> DataFrame:
    """(doc_id, lang_pred, score, accepted) of every whole text."""
    names = [k for k, v in model.items() if v]
    dicts = [model[k] for k in names]

    def run(batches):
        import zstandard as zs

        # short matches matter: common words are three letters long
        how = zs.ZstdCompressionParameters(compression_level=1, min_match=3, strategy=zs.STRATEGY_GREEDY, window_log=17, hash_log=15, chain_log=15, search_log=3, write_content_size=False)
        tools = []
        for d in dicts:
            d = zs.ZstdCompressionDict(d, dict_type=zs.DICT_TYPE_RAWCONTENT)
            d.precompute_compress(compression_params=how)
            tools.append(zs.ZstdCompressor(compression_params=how, dict_data=d))
        for whole in batches:
            for batch in slices(whole, "text"):
                out = []
                for v in batch.column(1):
                    text = v.as_py() or ""
                    if not tools or not LETTER.search(text):
                        out.append(("und", 0.0, False))
                        continue
                    data = clean(text).encode()
                    cuts = [data[i : i + chunk] for i in range(0, len(data), chunk)]
                    sizes = sorted((sum(len(t.compress(c)) for c in cuts), i) for i, t in enumerate(tools))
                    best = sizes[0][0]
                    second = sizes[1][0] if len(sizes) > 1 else len(data) + 12 * len(cuts)
                    gap = max(0.0, (second - best) / max(1, second))
                    out.append((names[sizes[0][1]], gap / (gap + margin), gap >= margin))
                cols = list(zip(*out, strict=True)) if out else [()] * 3
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(cols[0], pa.string()), pa.array(cols[1], pa.float64()), pa.array(cols[2], pa.bool_())], names=["doc_id", "lang_pred", "score", "accepted"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, lang_pred string, score double, accepted boolean")


def op5_language_id(spark, sf_dir) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    model = fit(docs.where(crc_mod(F.col("doc_id"), 3) != 1))
    held = crc_mod(F.col("doc_id"), 3) == 1
    return predict(docs, model).select("doc_id", held.alias("held_out"), "lang_pred", "score", F.col("accepted"))
