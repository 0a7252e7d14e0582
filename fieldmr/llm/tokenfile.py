"""Token ids of a corpus in ascending document order, written to and read back from coded segment files."""

from __future__ import annotations

import os
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import textbytes as tb
from .rans import Segment, encode
from .runtime import shared_dir

END_ID = 2
#: Tokens after which a segment is closed, at the end of a document.
SEGMENT_TOKENS = 4 << 20
#: Characters of text per writing task, about.
TASK_CHARS = 16 << 20
#: Distinct short words a worker remembers the ids of.
CACHE_WORDS = 1_500_000
#: Bytes of text whose words are looked up together.
LOOKUP_BYTES = 3 << 20

_loaded: dict[str, WordIds] = {}


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


#: Words of Latin letters alone: one token sequence each, ended by a word-final id.
_LATIN = re.compile("[A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+")


_WORD = np.ones(256, dtype=bool)
_WORD[[0x20, 0x0A]] = False
_MARK = np.zeros(256, dtype=bool)
_MARK[[0x2C, 0x2E]] = True
_LETTER = np.zeros(256, dtype=bool)
_LETTER[0x41:0x5B] = _LETTER[0x61:0x7B] = True


class WordIds:
    """Ids of blank-delimited words as bytes; unknown words are encoded by the tokenizer together and remembered.

    The tokenizer never joins characters across a blank, nor a letter with a comma or full stop after it, so the ids of a
    text are those of its words in turn.  Words are told apart by 64-bit hashes of a batch; each distinct one is
    looked up once.  When ``CACHE_WORDS`` are known, all are forgotten.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        vocabulary = self.tokenizer.get_vocab()
        self.final = np.zeros(max(vocabulary.values()) + 1, dtype=bool)
        self.final[[i for token, i in vocabulary.items() if token.endswith("</w>")]] = True
        self.forget()

    def forget(self) -> None:
        """Known words as arrays, some twenty bytes a word: sorted hashes, and where their ids lie in ``flat``."""
        self.keys = np.empty(0, dtype=np.uint64)
        self.begin = np.empty(0, dtype=np.int32)
        self.size = np.empty(0, dtype=np.int32)
        self.flat = np.empty(0, dtype="<u4")

    def _plain(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, dtype="<u4")

    def _letters(self, words: list[str]) -> list[np.ndarray]:
        out: list[np.ndarray] = []
        for i in range(0, len(words), 2_000):
            part = words[i : i + 2_000]
            ids = self._plain(" ".join(part))
            stop = np.flatnonzero(self.final[ids]) + 1
            out += np.split(ids, stop[:-1]) if len(stop) == len(part) else map(self._plain, part)
        return out

    def _learn(self, keys: np.ndarray, words: list[str]) -> None:
        """Add words with new hashes, which are sorted."""
        ids: list[np.ndarray] = [self.flat[:0]] * len(words)
        plain = [i for i, w in enumerate(words) if _LATIN.fullmatch(w)]
        for i, x in zip(plain, self._letters([words[i] for i in plain]), strict=True):
            ids[i] = x
        for i in set(range(len(words))).difference(plain):
            ids[i] = self._plain(words[i])
        size = np.fromiter(map(len, ids), np.int32, len(ids))
        begin = (len(self.flat) + np.cumsum(size) - size).astype(np.int32)
        at = np.searchsorted(self.keys, keys)
        self.flat = np.concatenate([self.flat, *ids])
        self.keys, self.begin, self.size = np.insert(self.keys, at, keys), np.insert(self.begin, at, begin), np.insert(self.size, at, size)

    def encode(self, data: np.ndarray, offsets: np.ndarray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids of some documents, an end id after each, and their numbers."""
        if len(self.keys) > CACHE_WORDS:
            self.forget()
        mark = np.flatnonzero(_MARK[data])
        mark = mark[mark > 0]
        ends_word = np.append(~_WORD[data], True)[mark + 1]
        edge = np.zeros(len(data) + 1, dtype=bool)
        edge[offsets] = True
        mark = mark[_LETTER[data[mark - 1]] & (ends_word | edge[mark + 1]) & ~edge[mark]]
        # a special token is lower case as written; anything else is folded anyway
        words = tb.Words(data, offsets, _WORD, lower=b"<|" not in data.tobytes(), cuts=mark)
        keys, first, number = np.unique(words.hashes, return_index=True, return_inverse=True)
        at = np.searchsorted(self.keys, keys)
        at[at == len(self.keys)] = 0
        new = np.flatnonzero(self.keys[at] != keys) if len(self.keys) else np.arange(len(keys))
        if len(new):
            self._learn(keys[new], [words.data[words.starts[j] : words.ends[j]].tobytes().decode() for j in first[new].tolist()])
            at = np.searchsorted(self.keys, keys)
        size, base, flat = self.size[at].astype(np.int64), self.begin[at].astype(np.int64), self.flat
        n = size[number]
        upto = np.concatenate(([0], np.cumsum(n)))
        per_doc = upto[words.bounds[1:]] - upto[words.bounds[:-1]]
        out = np.full(int(upto[-1]) + len(per_doc), end_id, dtype="<u4")
        to = np.arange(int(upto[-1]))
        out[to + np.repeat(np.arange(len(per_doc)), per_doc)] = flat[np.repeat(base[number] - upto[:-1], n) + to]
        return out, per_doc + 1


def _encoder(path: str) -> WordIds:
    if path not in _loaded:
        _loaded[path] = WordIds(path)
    return _loaded[path]


_SEGMENT = pa.schema([("part", pa.int64()), ("seg", pa.int64()), ("n_docs", pa.int64()), ("n_tokens", pa.int64()), ("no_id", pa.int64()), ("payload", pa.binary())])
SEGMENT_FIELDS = "part long, seg long, n_docs long, n_tokens long, no_id long, payload binary"


def _write(batches: Iterator[pa.RecordBatch], path: str, end_id: int, close_at: int) -> Iterator[pa.RecordBatch]:
    encoder, part, seg = _encoder(path), TaskContext.get().partitionId(), 0
    docs: list[np.ndarray] = []
    ids: list[np.ndarray] = []
    lengths: list[np.ndarray] = []
    held = no_id = 0

    def segment() -> pa.RecordBatch:
        n = np.concatenate(lengths)
        raw = encode(np.concatenate(ids), np.concatenate(docs), n)
        return pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in (part, seg, len(n), int(n.sum()), no_id)] + [pa.array([raw], pa.binary())], schema=_SEGMENT)

    for batch in batches:
        doc_id = batch.column(batch.schema.get_field_index("doc_id"))
        for i, j, data, offsets in tb.slices(tb.text_column(batch), LOOKUP_BYTES):
            coded, n = encoder.encode(data, offsets, end_id)
            own = doc_id.slice(i, j - i)
            # nulls sort first, so the documents without an id lead a part
            no_id += own.null_count
            docs.append(own.fill_null(0).to_numpy())
            ids.append(coded)
            lengths.append(n)
            held += len(coded)
            if held >= close_at:
                yield segment()
                docs, ids, lengths, held, no_id, seg = [], [], [], 0, 0, seg + 1
    if docs:
        yield segment()


def write_tokens(docs: DataFrame, path: str, tokenizer: str | None = None, end_id: int = END_ID, close_at: int = SEGMENT_TOKENS) -> None:
    """Write the ids of every document, each followed by ``end_id``, as segments at ``path``.

    Part and segment numbers follow ascending doc_id; one text per row, nulls as empty texts, null ids first,
    rows with one id in the order of their texts' hashes.
    """
    spark, tokenizer = docs.sparkSession, tokenizer or vocabulary()
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    chars = docs.agg(F.coalesce(F.sum(F.length("text")), F.lit(0))).first()[0]
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), chars // TASK_CHARS + 1)
    # ties go by a hash, so that rows repeating one id are also dealt over tasks
    ordered = docs.withColumn("tie", F.xxhash64("text")).repartitionByRange(int(tasks), "doc_id", "tie").sortWithinPartitions("doc_id", "tie", "text")
    ordered.select("doc_id", "text").mapInArrow(lambda it: _write(it, tokenizer, end_id, close_at), SEGMENT_FIELDS).write.option("compression", "none").parquet(path)


_READ = "part long, seg long, doc_id long, before long, n_tokens long, ids_crc32 long"


def _read(batches: Iterator[pa.RecordBatch], with_ids: bool) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for row in batch.to_pylist():
            segment = Segment(row["payload"])
            ids, lengths = segment.tokens().astype("<u4", copy=False), segment.doc_lengths
            stop = np.cumsum(lengths)
            raw, n = ids.view(np.uint8), len(lengths)
            begin = stop - lengths
            crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(begin.tolist(), stop.tolist(), strict=True)]
            doc_ids = pa.array(segment.doc_ids, mask=np.arange(n) < row["no_id"])
            arrays = [pa.array(np.full(n, row[k], dtype=np.int64)) for k in ("part", "seg")] + [doc_ids, pa.array(begin), pa.array(lengths), pa.array(crc, pa.int64())]
            names = ["part", "seg", "doc_id", "before", "n_tokens", "ids_crc32"]
            if with_ids:
                arrays.append(pa.array([ids[a:b] for a, b in zip(begin.tolist(), stop.tolist(), strict=True)], pa.list_(pa.int64())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(arrays, names=names)


def read_tokens(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32[, ids]) of every document in the segments at ``path``, all blocks checked."""
    segments = spark.read.schema(SEGMENT_FIELDS).parquet(path)
    counts = segments.select("part", "seg", "n_tokens")
    # prefix sums in two levels: inside parts, then over one row per part
    by_part = Window.partitionBy("part").orderBy("seg")
    inside = counts.select("part", "seg", (F.sum("n_tokens").over(by_part) - F.col("n_tokens")).alias("in_part"))
    parts = counts.groupBy("part").agg(F.sum("n_tokens").alias("n"))
    over = parts.select("part", (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("ahead"))
    ahead = inside.join(over, "part").select("part", "seg", (F.col("in_part") + F.col("ahead")).alias("ahead"))
    fields = _READ + ", ids array<long>" * with_ids
    rows = segments.select("part", "seg", "no_id", "payload").mapInArrow(lambda it: _read(it, with_ids), fields)
    start = (F.col("ahead") + F.col("before")).alias("start")
    return rows.join(ahead, ["part", "seg"]).select("doc_id", start, "n_tokens", "ids_crc32", *["ids"] * with_ids)


def token_table(docs: DataFrame, tokenizer: str | None = None) -> DataFrame:
    """Write the tokens of ``docs`` to the shared folder and read them back.

    Null text: only the end id.  Null doc_id: before all others.  Repeated rows: one entry each, side by side.  Texts of any
    length are encoded whole and stay in one segment.  Extra columns are not read; no documents give no rows.
    """
    import uuid

    spark = docs.sparkSession
    path = f"{shared_dir(spark)}/fieldmr-tokens-{uuid.uuid4().hex}"
    write_tokens(docs, path, tokenizer)
    return read_tokens(spark, path)
