"""Language identification by compression with per-language dictionaries.

A language is a raw-content dictionary: a bounded sample of its own text.  A text is cut into chunks of equal size, each
chunk is compressed with every dictionary, and the language with the smallest total wins.  A margin under
``narrow`` of the smallest total marks the answer as rejected; callers that need an answer for every
text still have the winner.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .runtime import broadcast_if_small, materialise

#: Bytes of sample text per language, and of each sampled document, at most.
SAMPLE_BYTES, PER_DOCUMENT = 96 << 10, 2 << 10
#: Bytes compressed at a time; short chunks keep the dictionary near.
CHUNK = 1 << 10
LEVEL = 6
#: Share of the smallest total by which the second has to be larger.
NARROW = 0.02
UNKNOWN = "und"

_LETTER = re.compile(r"[^\W\d_]")


def held_out(doc_id: Column) -> Column:
    """Documents that training never sees: crc32 of the id as text is divisible by 5."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def dictionaries(docs: DataFrame, sample: int = SAMPLE_BYTES, per_document: int = PER_DOCUMENT) -> dict[str, bytes]:
    """A bounded sample of text of every language, from documents that are not held out.

    The size of a sample is fixed: documents are taken in the order of a hash of their id until it is full.  The
    share of documents that enter the draw follows from each language's count, so the draw is small at any size.
    """
    usable = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (F.length(F.trim("text")) > 0) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    counts = materialise(usable.groupBy("lang").count(), "langs")
    # four times as many documents as full pieces fit, as many texts are shorter than a piece
    want = 8 * sample // per_document + 64
    draw = F.shiftrightunsigned("h", 11) / F.lit(float(1 << 53)) * F.col("count") <= want
    drawn = (
        usable.join(broadcast_if_small(counts), "lang")
        .select("lang", "count", F.xxhash64("doc_id").alias("h"), "doc_id", F.substring("text", 1, per_document).alias("piece"))
        .where(draw).select("lang", "h", "doc_id", "piece")
    )
    by_lang: dict[str, list] = {}
    for row in sorted(drawn.collect(), key=lambda r: (r.lang, r.h, r.doc_id, r.piece)):
        by_lang.setdefault(row.lang, []).append(row.piece)
    out = {}
    # frequent languages first: the order breaks ties
    share = {r["lang"]: r["count"] for r in counts.collect()}
    for lang, pieces in sorted(by_lang.items(), key=lambda x: (-share[x[0]], x[0])):
        taken, size = [], 0
        for piece in pieces:
            raw = folded(piece)[:per_document]
            if size + len(raw) > sample:
                break
            taken.append(raw)
            size += len(raw)
        out[lang] = b"\n".join(taken) or folded(pieces[0])[:sample]
    return out


def folded(text: str) -> bytes:
    """What is compressed: case says nothing about the language."""
    return text.lower().encode()


class Classifier:
    def __init__(self, samples: dict[str, bytes], level: int = LEVEL):
        self.langs = list(samples)
        self.compressors = []
        for lang in self.langs:
            entry = zstandard.ZstdCompressionDict(samples[lang], dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            entry.precompute_compress(level=level)
            self.compressors.append(zstandard.ZstdCompressor(level=level, dict_data=entry, write_checksum=False, write_content_size=False))

    def sizes(self, raw: bytes) -> list[int]:
        chunks = [raw[i : i + CHUNK] for i in range(0, len(raw), CHUNK)]
        return [sum(len(c.compress(x)) for x in chunks) for c in self.compressors]

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        """(language, score, rejected); ties go to the language that was first given."""
        if not text or not self.langs or not _LETTER.search(text):
            return UNKNOWN, 0.0, True
        totals = self.sizes(folded(text))
        order = sorted(range(len(totals)), key=lambda k: (totals[k], k))
        if len(order) == 1:
            return self.langs[0], 1.0, False
        margin = (totals[order[1]] - totals[order[0]]) / totals[order[1]]
        return self.langs[order[0]], min(1.0, margin / (margin + NARROW)), margin < NARROW


_models: dict[int, Classifier] = {}


def _predict(batches: Iterator[pa.RecordBatch], shared: Broadcast) -> Iterator[pa.RecordBatch]:
    key = hash(tuple(shared.value.items()))
    model = _models.get(key)
    if model is None:
        _models.clear()
        model = _models[key] = Classifier(shared.value)
    for batch in batches:
        said = [model.predict(t.as_py()) for t in batch.column("text")]
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), batch.column("held_out"), pa.array([s[0] for s in said], pa.string()), pa.array([s[1] for s in said], pa.float64()), pa.array([s[2] for s in said], pa.bool_())],
            names=["doc_id", "held_out", "lang_pred", "score", "rejected"],
        )


def identify_languages(docs: DataFrame) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, rejected) for each row of ``docs`` (doc_id, text, lang, ...).

    Dictionaries come from rows that are not held out; a prediction sees the text alone.  Null text and text without a
    letter: ``und``, score 0, rejected.  A null doc_id is not held out and not trained on.  With no labelled row every answer is
    ``und``.  Repeated rows give a row each; texts of any length are compressed whole.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    shared = docs.sparkSession.sparkContext.broadcast(dictionaries(docs))
    rows = docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text")
    return rows.mapInArrow(lambda it: _predict(it, shared), "doc_id long, held_out boolean, lang_pred string, score double, rejected boolean")
