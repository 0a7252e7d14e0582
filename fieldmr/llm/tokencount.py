"""Greedy word-piece lengths with one pass of an automaton, building no pieces.

The vocabulary is a trie with failure links.  When no edge fits, the link says how many pieces the longest-match
segmentation has finished by then and where it goes on, so a word's count is a sum of precomputed numbers.
Links are resolved ahead of time into one table (state, byte class) -> (state, finished pieces), and a batch of
words runs through it column by column.
"""

from __future__ import annotations

import json
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textbytes as tb


class Automaton:
    """Counts pieces of words: the first from ``initial``, others from ``continuation``; a word that cannot be cut counts one."""

    def __init__(self, initial: Iterable[bytes], continuation: Iterable[bytes] | None = None):
        initial = set(initial) - {b""}
        rest = initial if continuation is None else set(continuation) - {b""}
        same = continuation is None or rest == initial
        children: list[dict[int, int]] = [{}]
        accepts, depth_of, parent, via = [False], [0], [-1], [0]

        def grow(root: int, pieces: Iterable[bytes]) -> None:
            for piece in pieces:
                at = root
                for c in piece:
                    nxt = children[at].get(c)
                    if nxt is None:
                        nxt = len(children)
                        children[at][c] = nxt
                        children.append({}), accepts.append(False), depth_of.append(depth_of[at] + 1), parent.append(at), via.append(c)
                    at = nxt
                accepts[at] = True

        grow(0, initial)
        again = 0
        if not same:
            again = len(children)
            children.append({}), accepts.append(False), depth_of.append(0), parent.append(-1), via.append(0)
            grow(again, rest)
        n = len(children)
        dead = n
        # bytes that start or continue nothing but themselves behave alike
        used = sorted({c for node in children for c in node})
        self.classes = np.full(256, len(used), dtype=np.int64)
        self.classes[used] = np.arange(len(used))
        width = len(used) + 1
        step = np.full((n + 1, width), dead, dtype=np.int32)
        pops = np.zeros((n + 1, width), dtype=np.uint16)
        fail = np.full(n, dead, dtype=np.int64)
        popped = np.zeros(n, dtype=np.int64)
        #: Pieces that are still to be counted where a word ends, -1 if it cannot be cut.
        self.final = np.full(n + 1, -1, dtype=np.int64)
        for root in {0, again}:
            self.final[root] = 0
        for v in sorted(range(n), key=lambda v: depth_of[v]):
            if depth_of[v] == 0:
                for c, w in children[v].items():
                    step[v, self.classes[c]] = w
                continue
            if accepts[v]:
                fail[v], popped[v] = again, 1
            else:
                z, k = fail[parent[v]], self.classes[via[v]]
                # the table of a shorter string already has its links resolved
                if z != dead and step[z, k] != dead:
                    fail[v], popped[v] = step[z, k], popped[parent[v]] + pops[z, k]
            z = fail[v]
            if z != dead:
                step[v] = step[z]
                pops[v] = pops[z] + popped[v]
                if self.final[z] >= 0:
                    self.final[v] = popped[v] + self.final[z]
            for c, w in children[v].items():
                step[v, self.classes[c]] = w
                pops[v, self.classes[c]] = 0
        self.width, self.dead, self.step, self.pops = width, dead, step.ravel(), pops.ravel()

    def counts(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Pieces of each word data[start : end]."""
        order = np.argsort(starts - ends, kind="stable")  # longest first
        begin, length = starts[order], (ends - starts)[order]
        state = np.zeros(len(order), dtype=np.int64)
        total = np.zeros(len(order), dtype=np.int64)
        live = len(order)
        classes = self.classes[data]
        for j in range(int(length[0]) if len(length) else 0):
            while live and length[live - 1] <= j:
                live = int(np.searchsorted(-length, -j, side="left"))
            at = state[:live] * self.width + classes[begin[:live] + j]
            total[:live] += self.pops[at]
            state[:live] = self.step[at]
        out = np.empty(len(order), dtype=np.int64)
        out[order] = np.where(self.final[state] >= 0, total + self.final[state], 1)
        return out


def pieces_of(path: str) -> frozenset[bytes]:
    """Byte strings of a public byte-level vocabulary file, word-end marks taken off."""
    vocabulary = json.load(open(path, encoding="utf-8"))["model"]["vocab"]
    # bytes that do not print stand at code points from 256 on, in order
    prints = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    other = [b for b in range(256) if b not in set(prints)]
    byte_of = {chr(b): b for b in prints} | {chr(256 + i): b for i, b in enumerate(other)}
    return frozenset(bytes(byte_of[c] for c in token.removesuffix("</w>")) for token in vocabulary)


@lru_cache(maxsize=2)
def automaton(path: str) -> Automaton:
    return Automaton(pieces_of(path))


def _count(batches: Iterator[pa.RecordBatch], path: str) -> Iterator[pa.RecordBatch]:
    machine = automaton(path)
    for batch in batches:
        ids = batch.column(batch.schema.get_field_index("doc_id"))
        for i, j, data, offsets in tb.slices(tb.text_column(batch)):
            words = tb.Words(data, offsets, tb.NON_SPACE)
            totals = np.concatenate(([0], np.cumsum(machine.counts(words.data, words.starts, words.ends))))
            per_doc = totals[words.bounds[1:]] - totals[words.bounds[:-1]]
            yield pa.RecordBatch.from_arrays([ids.slice(i, j - i), pa.array(words.per_doc, pa.int64()), pa.array(per_doc, pa.int64())], names=["doc_id", "n_words", "n_tokens"])


def count_tokens(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """(doc_id, n_words, n_tokens) for each row of ``docs``: pieces of its lower-cased (A-Z) blank-delimited words.

    Null and blank texts count 0.  Repeated rows, null ids and ties give a row each as they are; texts and words of any length
    are counted whole; extra columns are not read; no documents give no rows.
    """
    if vocabulary is None:
        import public_tokenizers

        vocabulary = public_tokenizers.path("word_bpe_49k.json")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(lambda it: _count(it, vocabulary), "doc_id long, n_words long, n_tokens long")
