"""Benchmark decontamination by BM25 retrieval and overlap checks.

Benchmark items are cut into segments of at most ``SEGMENT`` words; an inverted
index holds each term's segments with their BM25 impact, divided by the score that
the segment gives itself, in blocks that know their largest impact. Document
frequencies come from the whole corpus of training documents. Every passage
(``PASSAGE`` words, ``STRIDE`` apart, so that a segment lies whole in one) is a query
for all segments that score at least ``THRESHOLD`` of their own score.

A segment's most frequent terms, up to half the threshold in impact, are not
enough to reach it; so a passage whose other terms, at their best, fall short needs
no query. That bound is summed for all passages of a batch at once; those that pass
go through block-max WAND. A hit counts when 4-grams of both the item's question
and its answer (``question_answer``)
lie in the document near the passage.

The benchmark is read in blocks of bounded size, each broadcast; documents are
scanned once per block for frequencies and once for passages.

Edge cases: items with fewer than ``LEAST_WORDS`` words count only where they stand word
for word in the text, and those with fewer than ``GRAM`` words (less than one n-gram) are
not evidence and are left out; null and empty texts match nothing; repeated items match each; a null document
id is carried through; empty tables give no rows; other columns are ignored.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_left
from collections import Counter, defaultdict
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronopath.llm.common import MEMO_ENTRIES, lower_words, slices

SEGMENT, PASSAGE, STRIDE = 64, 96, 32
THRESHOLD, K1, B = 0.6, 1.2, 0.75
QUESTION_OVERLAP, ANSWER_OVERLAP, GRAM, LEAST_WORDS, LEAST_ANSWER = 0.7, 0.5, 4, 8, 8
#: Characters of benchmark text indexed and broadcast together.
BLOCK_CHARS = 16_000_000
POSTING_BLOCK = 64
_EDGES = b".,;:!?\"'()[]{}"


def terms(text: str | None) -> list[bytes]:
    """Lower-case words without punctuation at their ends; bare punctuation is left out."""
    return [w for w in (w.strip(_EDGES) for w in lower_words(text)) if w]


def question_answer(text: str) -> tuple[list[bytes], list[bytes]]:
    """An item's last sentence is its answer, or its last quarter if it is one sentence.

    An answer of few words takes in the words before it, up to ``LEAST_ANSWER`` or half of
    the item: a word or two say nothing, and text that follows may run into the last.
    """
    own, parts = terms(text), [t for t in (terms(s) for s in re.split(r"(?<=[.?!])\s+|\n", text)) if t]
    last = len(parts[-1]) if len(parts) > 1 else len(own) // 4
    cut = len(own) - min(max(last, LEAST_ANSWER), max(last, len(own) // 2))
    return own[:cut], own[cut:]


class Index:
    """Block-max index of segments; impacts are shares of a segment's own score."""

    def __init__(self, items: list[tuple], frequency: dict[bytes, int], n_docs: int, threshold: float = THRESHOLD, average: float | None = None):
        self.threshold, self.items, self.segments = threshold, [], []
        for key, text in items:
            words = terms(text)
            if len(words) < GRAM:
                continue
            self.items.append((key, [], words) if len(words) < LEAST_WORDS else (key, *question_answer(text)))
            pieces = max(1, -(-len(words) // SEGMENT))
            size = -(-len(words) // pieces)
            self.segments += [(len(self.items) - 1, words[i : i + size]) for i in range(0, len(words), size)]
        self.vocabulary = {t: k for k, t in enumerate(sorted({t for _, words in self.segments for t in words}))}
        self.words = sum(len(w) for _, w in self.segments)
        average = average or self.words / max(1, len(self.segments))
        names = list(self.vocabulary)
        idf = [math.log1p((n_docs - min(n_docs, frequency.get(t, 0)) + 0.5) / (frequency.get(t, 0) + 0.5)) for t in names]
        lists: dict[int, list[tuple[int, float]]] = defaultdict(list)
        self.need = np.zeros(len(names) + 1)  # the last entry stands for terms outside the vocabulary
        for k, (_, words) in enumerate(self.segments):
            norm = K1 * (1 - B + B * len(words) / average)
            impact = {self.vocabulary[t]: idf[self.vocabulary[t]] * n * (K1 + 1) / (n + norm) for t, n in Counter(words).items()}
            total, common = sum(impact.values()), 0.0
            for t in sorted(impact, key=lambda t: (idf[t], t)):
                share = impact[t] / total
                lists[t].append((k, share))
                if common + share <= threshold / 2:
                    common += share
                else:
                    self.need[t] = max(self.need[t], share / (threshold - common))
        self.lists = {t: ([k for k, _ in p], [s for _, s in p]) for t, p in lists.items()}
        self.best = {t: max(s) for t, (_, s) in self.lists.items()}
        self.block_best = {t: [max(s[i : i + POSTING_BLOCK]) for i in range(0, len(s), POSTING_BLOCK)] for t, (_, s) in self.lists.items()}

    def retrieve(self, query: set[int]) -> list[tuple[int, float]]:
        """(segment, score) of all segments that reach the threshold, by block-max WAND."""
        at = {t: 0 for t in query if t in self.lists}
        out, bar = [], self.threshold - 1e-9

        def head(t: int) -> int:
            return self.lists[t][0][at[t]]

        def skip(t: int, to: int) -> None:
            at[t] = bisect_left(self.lists[t][0], to, at[t])
            if at[t] == len(self.lists[t][0]):
                del at[t]

        while at:
            order = sorted(at, key=head)
            bound, pivot = 0.0, None
            for i, t in enumerate(order):
                bound += self.best[t]
                if bound >= bar:
                    pivot = head(t)
                    while i + 1 < len(order) and head(order[i + 1]) == pivot:
                        i += 1
                    ahead = order[: i + 1]
                    break
            if pivot is None:
                break
            places = {t: bisect_left(self.lists[t][0], pivot, at[t]) for t in ahead}
            inside = [(t, p // POSTING_BLOCK) for t, p in places.items() if p < len(self.lists[t][0])]
            if sum(self.block_best[t][b] for t, b in inside) >= bar:
                if head(order[0]) == pivot:
                    score = sum(self.lists[t][1][at[t]] for t in ahead)
                    if score >= bar:
                        out.append((pivot, score))
                    for t in ahead:
                        skip(t, pivot + 1)
                else:
                    for t in ahead:
                        if head(t) < pivot:
                            skip(t, pivot)
            else:  # nothing in these blocks can reach the bar: go on behind the nearest block end, or to the next list
                ends = [self.lists[t][0][min(len(self.lists[t][0]), (b + 1) * POSTING_BLOCK) - 1] + 1 for t, b in inside]
                to = min([*ends, *(head(t) for t in order[len(ahead) :][:1])])
                for t in ahead:
                    skip(t, max(to, pivot + 1))
        return out


class Encoder(dict):
    """Word of a text -> its number in the vocabulary, -1 outside, -2 for bare punctuation."""

    def __init__(self, vocabulary: dict[bytes, int]):
        self.vocabulary = vocabulary

    def __missing__(self, word: bytes) -> int:
        if len(self) >= MEMO_ENTRIES:
            self.clear()
        bare = word.strip(_EDGES)
        self[word] = found = self.vocabulary.get(bare, -1) if bare else -2
        return found

    def array(self, words: list[bytes]) -> np.ndarray:
        ids = np.fromiter(map(self.__getitem__, words), np.int64, len(words))
        return ids[ids > -2]


def frequencies(docs: DataFrame, vocabulary: dict[bytes, int]) -> tuple[dict[bytes, int], int]:
    """(documents that hold each term, all documents): at most one number a term reaches the driver."""
    shared = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, n, encoder = np.zeros(len(shared.value), np.int64), 0, Encoder(shared.value)
        for batch in slices(batches):
            for text in batch.column(0).to_pylist():
                ids = np.unique(encoder.array(lower_words(text)))
                counts[ids[ids >= 0]] += 1
                n += 1
        found = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(np.r_[found, -1]), pa.array(np.r_[counts[found], n])], names=["term", "n"])

    rows = docs.select("text").mapInArrow(run, "term long, n long").groupBy("term").agg(F.sum("n").alias("n")).toArrow().to_pandas()
    names, found = list(vocabulary), dict(zip(rows.term, rows.n))
    return {names[t]: int(n) for t, n in found.items() if t >= 0}, int(found.get(-1, 0))


def share(part: list[bytes], near: set[tuple], sizes: int) -> float:
    """Share of a part's word n-grams that occur in ``near``; 1 for an empty part."""
    size = min(sizes, len(part))
    grams = [tuple(part[i : i + size]) for i in range(len(part) - size + 1)] if part else []
    return sum(g in near for g in grams) / len(grams) if grams else 1.0


def overlaps(question: list[bytes], answer: list[bytes], region: list[bytes]) -> tuple[float, float]:
    sizes = {min(GRAM, len(p)) for p in (question, answer) if p}
    near = {tuple(region[i : i + n]) for n in sizes for i in range(len(region) - n + 1)}
    return share(question, near, GRAM), share(answer, near, GRAM)


def holds(region: list[bytes], part: list[bytes]) -> bool:
    return any(region[i : i + len(part)] == part for i in range(len(region) - len(part) + 1))


def matches(docs: DataFrame, index: Index, item_type: str) -> DataFrame:
    """(id, item, score, question_overlap, answer_overlap) of (id, text) for one index block."""
    shared = docs.sparkSession.sparkContext.broadcast(index)
    kinds = {"long": pa.int64(), "bigint": pa.int64(), "int": pa.int32(), "string": pa.string()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = shared.value
        encoder = Encoder(index.vocabulary)
        for batch in slices(batches):
            texts = batch.column(1).to_pylist()
            ids = [encoder.array(lower_words(t)) for t in texts]
            total = np.concatenate([[0.0], np.cumsum(index.need[np.concatenate([*ids, np.zeros(0, np.int64)])])])
            begins = np.concatenate([[0], np.cumsum([len(x) for x in ids])])
            rows = []
            for k, own in enumerate(ids):
                starts = np.arange(0, max(1, len(own) - PASSAGE + STRIDE), STRIDE)
                ends = np.minimum(starts + PASSAGE, len(own))
                open_ = starts[total[begins[k] + ends] - total[begins[k] + starts] >= 1 - 1e-9]
                hits: dict[int, list[tuple[float, int]]] = {}
                for s in open_.tolist():
                    query = np.unique(own[s : s + PASSAGE])
                    if index.need[query].sum() < 1 - 1e-9:
                        continue
                    for segment, score in index.retrieve(set(query[query >= 0].tolist())):
                        item = index.segments[segment][0]
                        hits.setdefault(item, []).append((score, s))
                if hits:
                    words = terms(texts[k])
                for item, found in hits.items():
                    key, question, answer = index.items[item]
                    reach = PASSAGE + len(question) + len(answer)
                    for score, s in sorted(set(found), reverse=True):  # the first passage around which the item is found
                        region = words[max(0, s - reach) : s + reach + PASSAGE]
                        q, a = overlaps(question, answer, region) if question else (1.0, float(holds(region, answer)))
                        if q >= QUESTION_OVERLAP and a >= ANSWER_OVERLAP:
                            rows.append((k, key, score, q, a))
                            break
            picked = pa.array([r[0] for r in rows], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(picked), pa.array([r[1] for r in rows], kinds[item_type]), *(pa.array([r[i] for r in rows], pa.float64()) for i in (2, 3, 4))], names=["id", "item", "score", "question_overlap", "answer_overlap"])

    return docs.mapInArrow(run, f"id {docs.schema['id'].dataType.simpleString()}, item {item_type}, score double, question_overlap double, answer_overlap double")


def contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """A row for each document and benchmark item that it holds."""
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    items = benchmark.select(F.col(item_col).alias("item"), F.col(item_text).cast("string").alias("text")).where("text is not null")
    (chars,) = items.agg(F.sum(F.char_length("text"))).first()
    blocks = max(1, -(-(chars or 0) // BLOCK_CHARS))
    kind = items.schema["item"].dataType.simpleString()
    block = lambda k: [tuple(r) for r in items.where(F.pmod(F.xxhash64("item", "text"), F.lit(blocks)) == k).orderBy("item", "text").collect()]
    sizes = [(plain.words, len(plain.segments)) for plain in (Index(block(k), {}, 0) for k in range(blocks))]
    average = sum(n for n, _ in sizes) / max(1, sum(k for _, k in sizes))  # over all blocks, so that a score does not depend on them
    found = []
    for k in range(blocks):
        rows = block(k)
        found.append(matches(source, Index(rows, *frequencies(source, Index(rows, {}, 0).vocabulary), average=average), kind))
    return reduce(DataFrame.unionByName, found).withColumnsRenamed({"id": id_col, "item": item_col})


def op1_decontaminate(spark, sf_dir: str) -> DataFrame:
    return contaminated(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
