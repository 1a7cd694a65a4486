"""Toxicity by two class-conditional Kneser-Ney models over the bytes of words.

Words of the labelled documents are counted by class in Spark, then turned into
n-grams of bytes (a word's first bytes follow blanks, its last is followed by
one). Each class has its own discounted counts at the highest order and backs off
to one distribution of continuation counts that both share. For an n-gram that
neither class has seen, that shared factor is the same on both sides, so only the
ratio of the back-off weights is left: a scorer needs two numbers an n-gram.

Every n-gram keeps counts of its own in a table. All shorter forms and the context
of an n-gram share the two bytes before its last one, so the back-off is worked out
for each such pair apart, given the probabilities of two bytes (65,536 at most),
which come from the whole table. Texts are read in blocks that ask for the ratios
of their distinct words; equal words of all blocks meet in shards, which ask for their
distinct n-grams. The answers meet the blocks when these are read a second time, so texts
move once. Neither the driver nor an executor ever holds a whole table.

A text's evidence is the log-likelihood ratio divided by length: over the whole
text, over its strongest spans of 1, 8 and 64 words, and counting only what single
words have beyond a floor; a logistic fit on
labelled rows whose counts the models did not see turns these into a score.

Edge cases: null and empty texts have no evidence and get the score of a zero
ratio; documents without a label are scored only; with one class missing from the
training rows every score is the share of label 1 among them (0 with none at
all); repeated rows count and are scored each; other columns pass through.
"""

from __future__ import annotations

import hashlib
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from chronopath.llm.common import MEMO_ENTRIES, Scratch, WordColumn, give_back, lower_words, mix, slices
from chronopath.llm.labelled import attach, fold, logistic, sigmoid

ORDER, DISCOUNT = 8, 0.75
#: Bytes of text packed together and cut into words at once, shards of words and n-grams at least, words cut into n-grams at once. They bound memory only.
BLOCK_BYTES, PART_BYTES, SHARDS, WORDS_AT_ONCE = 8 << 20, 1 << 20, 16, 20_000
SPANS, FLOORS = (1, 8, 64), (2, 4)
#: Labelled rows (about) that are kept from the counts and fit the score; one in CALIBRATION_FOLDS if there are fewer.
CALIBRATION_ROWS, CALIBRATION_FOLDS = 20_000, 5
THRESHOLD = 0.3
EVIDENCE = {"mean_ratio": "double"} | {f"span_{n}": "double" for n in SPANS} | {f"above_{n}": "double" for n in FLOORS}
FEATURES, N_EVIDENCE = {"score": "double"} | EVIDENCE, len(EVIDENCE)


def grams(tokens: list[bytes], order: int = ORDER) -> tuple[np.ndarray, np.ndarray]:
    """(n-grams as integers, latest byte lowest; index of the word each belongs to)."""
    text = np.frombuffer((b" " * (order - 1)).join([b"", *tokens, b""]), np.uint8).astype(np.uint64)
    n = len(text) - order + 1
    if n <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    key = np.zeros(n, np.uint64)
    for k in range(order):
        key = key << np.uint64(8) | text[k : k + n]
    last, before = text[order - 1 :], text[order - 2 : -1]
    inside = (last != 32) | (before != 32)
    word = np.cumsum((last != 32) & (before == 32)) - 1
    return key[inside], word[inside]


@dataclass
class Model:
    table: DataFrame | None  # (key, seen, unseen): log ratio of each n-gram seen in training, and of its context's back-off weights
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    constant: float | None = None


def evidence(ratio: np.ndarray) -> list[float]:
    """Length-normalised log-likelihood ratio: of the text, of its strongest span of each size, above each floor."""
    if not len(ratio):
        return [0.0] * N_EVIDENCE
    total = np.concatenate([[0.0], np.cumsum(ratio)])
    whole = total[-1] / len(ratio)
    spans = [float((total[n:] - total[:-n]).max() / n) if len(ratio) >= n else whole for n in SPANS]
    return [whole, *spans, *(float(np.maximum(ratio - floor, 0).mean()) for floor in FLOORS)]


def word_counts(labelled: DataFrame) -> DataFrame:
    """(word, toxic, ordinary) occurrences, out of (id, text, label)."""

    def rows(counts: list[Counter]) -> pa.RecordBatch:
        seen = list(set(counts[0]) | set(counts[1]))
        return pa.RecordBatch.from_arrays([pa.array(seen, pa.binary()), pa.array([counts[1][w] for w in seen], pa.int64()), pa.array([counts[0][w] for w in seen], pa.int64())], names=["word", "toxic", "ordinary"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = [Counter(), Counter()]
        for batch in slices(batches):
            for text, label in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                counts[label > 0].update(lower_words(text))
            if len(counts[0]) + len(counts[1]) > MEMO_ENTRIES:
                yield rows(counts)
                counts = [Counter(), Counter()]
        yield rows(counts)

    return labelled.select("text", "label").mapInArrow(run, "word binary, toxic long, ordinary long").groupBy("word").agg(F.sum("toxic").alias("toxic"), F.sum("ordinary").alias("ordinary"))


def gram_counts(words: DataFrame) -> DataFrame:
    """(key, toxic, ordinary): a row for each n-gram."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            key, word = grams(batch.column(0).to_pylist())
            found, at = np.unique(key, return_inverse=True)
            sums = [np.bincount(at, np.asarray(batch.column(i), dtype=np.float64)[word], minlength=len(found)).astype(np.int64) for i in (1, 2)]
            yield pa.RecordBatch.from_arrays([pa.array(found.view(np.int64)), *map(pa.array, sums)], names=["key", "toxic", "ordinary"])

    return words.mapInArrow(run, "key long, toxic long, ordinary long").groupBy("key").agg(F.sum("toxic").alias("toxic"), F.sum("ordinary").alias("ordinary"))


def continuation(keys: np.ndarray, order: int, pairs: np.ndarray | None = None) -> np.ndarray:
    """Kneser-Ney probability of each n-gram's last byte given the others, from the number
    of different left neighbours; ``keys`` has an n-gram once for each of these. With
    ``pairs``, the probabilities of all two bytes, ``keys`` may be only those n-grams that
    have certain two bytes before the last."""
    levels = []
    for k in range(order, 0 if pairs is None else 2, -1):
        keys_here = keys if k == order else levels[-1][0] & _low(k)
        found, n = np.unique(keys_here, return_counts=True)
        levels.append((found, n.astype(np.float32)))
    if pairs is None:
        found, n = levels.pop()
        p = (0.999 * n / n.sum() + 0.001 / 256).astype(np.float32)
    else:
        found, p = np.arange(1 << 16, dtype=np.uint64), pairs
    while levels:
        shorter, low = found, p
        found, n = levels.pop()
        k = order - len(levels)
        first = np.flatnonzero(np.diff(found >> np.uint64(8), prepend=np.uint64(1 << 63)))  # n-grams of one context lie together
        size = np.diff(np.r_[first, len(found)])
        total, follow = np.repeat(np.add.reduceat(n, first), size), np.repeat(size, size).astype(np.float32)
        p = (np.maximum(n - DISCOUNT, 0) + DISCOUNT * follow * low[np.searchsorted(shorter, found & _low(k - 1))]) / total
    return p[np.searchsorted(found, keys)]


def _low(k: int) -> np.uint64:
    """Mask of the last k bytes."""
    return np.uint64((1 << 8 * k) - 1)


def pair_probabilities(counts: DataFrame) -> np.ndarray:
    """Continuation probability of each two bytes, from the different bytes before them in the whole table."""
    three = counts.select(F.col("key").bitwiseAND(0xFFFFFF).alias("three")).distinct()
    pair, n = (c.to_numpy() for c in three.groupBy(F.col("three").bitwiseAND(0xFFFF).alias("pair")).agg(F.count("*").alias("n")).toArrow().columns)
    first = np.cumsum(n) - n
    out = np.zeros(1 << 16, np.float32)
    out[pair] = continuation(np.repeat(pair.astype(np.uint64), n), 2)[first]
    return out


def ratios(keys: np.ndarray, toxic: np.ndarray, ordinary: np.ndarray, pairs: np.ndarray, order: int = ORDER) -> tuple[np.ndarray, np.ndarray]:
    """Log ratio of each n-gram and of its context's back-off weights; all n-grams of a context come together."""
    shared = continuation(keys & _low(order - 1), order - 1, pairs)
    _, at = np.unique(keys >> np.uint64(8), return_inverse=True)
    logs, weights = [], []
    for counts in (toxic, ordinary):
        total, follow = (np.bincount(at, x).astype(np.float32) for x in (counts, counts > 0))
        weight = np.where(total > 0, DISCOUNT * follow / np.maximum(total, 1), np.float32(1))
        logs.append(np.log(np.maximum(counts - DISCOUNT, 0) / np.maximum(total, 1)[at] + weight[at] * shared))
        weights.append(np.log(weight))
    return logs[0] - logs[1], (weights[0] - weights[1])[at]


def ratio_table(counts: DataFrame) -> DataFrame:
    """(key, seen, unseen) of (key, toxic, ordinary)."""
    pairs = pair_probabilities(counts)

    def run(rows: pa.Table) -> pa.Table:
        key, toxic, ordinary = (rows.column(c).to_numpy() for c in ("key", "toxic", "ordinary"))
        found = ratios(key.view(np.uint64), toxic, ordinary, pairs)
        return pa.table([pa.array(key), *(pa.array(x.astype(np.float32)) for x in found)], names=["key", "seen", "unseen"])

    middle = F.shiftright("key", 8).bitwiseAND(0xFFFF)
    return counts.withColumn("middle", middle).groupBy("middle").applyInArrow(run, "key long, seen float, unseen float")


def shard(keys: np.ndarray, shards: int) -> np.ndarray:
    """Part of the table that knows an n-gram and its context."""
    return (mix(keys >> np.uint64(8)) % np.uint64(shards)).astype(np.int32)


def look_up(asked: np.ndarray, keys: np.ndarray, seen: np.ndarray, unseen: np.ndarray) -> np.ndarray:
    """Log ratio of each n-gram asked for: its own, else its context's, else 0; ``keys`` are sorted."""
    out = np.zeros(len(asked), np.float32)
    for shift, values in ((8, unseen), (0, seen)):
        known, wanted = keys >> np.uint64(shift), asked >> np.uint64(shift)
        at = np.searchsorted(known, wanted)
        hit = np.flatnonzero(at < len(known))
        hit = hit[known[at[hit]] == wanted[hit]]
        out[hit] = values[at[hit]]
    return out


def blocks(batches: Iterator[pa.RecordBatch], at: int) -> Iterator[pa.RecordBatch]:
    """The rows again, in blocks cut by the bytes of text alone, so that any columns beside the text give the same blocks."""

    def joined() -> pa.RecordBatch:
        out = pa.Table.from_batches(parts).combine_chunks().to_batches()[0]
        parts.clear()
        return out

    parts, size = [], 0
    for batch in batches:
        sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(at)), 0), dtype=np.int64)
        ends, done = np.cumsum(sizes), 0
        while done < batch.num_rows:
            base = ends[done - 1] if done else 0
            to = int(np.searchsorted(ends, base + BLOCK_BYTES - size, "left")) + 1
            parts.append(batch.slice(done, to - done))
            size += int(ends[min(to, batch.num_rows) - 1] - base)
            done = to
            if size >= BLOCK_BYTES:
                size = 0
                yield joined()
        if parts:  # a copy of the rest, so that the whole batch need not stay
            parts[-1] = parts[-1].take(pa.array(np.arange(parts[-1].num_rows)))
        del batch
    if parts:
        yield joined()


def block_name(column: pa.Array) -> bytes:
    """Digest of a block's texts."""
    column = pc.fill_null(column, "").cast(pa.large_string())
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    found = hashlib.blake2b(memoryview(data)[offsets[0] : offsets[-1]] if data else b"", digest_size=16)
    found.update((offsets - offsets[0]).tobytes())
    return found.digest()


class Block:
    """A block of texts, whose words are taken from some texts at a time, and its distinct words' hashes in order."""

    def __init__(self, column: pa.Array):
        self.texts = pa.RecordBatch.from_arrays([column], names=["text"])
        self.hashes = np.unique(np.concatenate([np.zeros(0, np.uint64), *(np.unique(words.hashes) for words in self.parts())]))

    def parts(self) -> Iterator[WordColumn]:
        return (WordColumn(texts.column(0), lower=True) for texts in slices([self.texts], limit=PART_BYTES))

    def places(self, words: WordColumn) -> np.ndarray:
        """Of each word of a part, its place among the distinct ones."""
        found, at = np.unique(words.hashes, return_inverse=True)
        return np.searchsorted(self.hashes, found)[at]

    def homes(self, shards: int) -> np.ndarray:
        return (self.hashes % np.uint64(shards)).astype(np.int32)

    def asked(self, shards: int) -> Iterator[tuple[int, bytes]]:
        """(shard, its words joined by spaces) of each shard."""
        found, left, home = np.empty(len(self.hashes), object), np.ones(len(self.hashes), bool), self.homes(shards)
        for words in self.parts():
            hashes, first = np.unique(words.hashes, return_index=True)
            at, data = np.searchsorted(self.hashes, hashes), words.data.tobytes()
            first, at = first[left[at]], at[left[at]]
            left[at] = False
            for k, a, b in zip(at.tolist(), *(x[first].tolist() for x in words.spans)):
                found[k] = data[a:b]
        for k in np.unique(home).tolist():
            yield k, b" ".join(found[home == k].tolist()).lower()


def asked_words(docs: DataFrame, text_col: str, shards: int) -> DataFrame:
    """(block, shard, words): the distinct words of each block, by the shard that answers for them."""

    def ask(rows: pa.RecordBatch) -> pa.RecordBatch:
        found = [(k, zlib.compress(w, 3)) for k, w in Block(rows.column(0)).asked(shards)]
        give_back()
        return pa.RecordBatch.from_arrays([pa.array([block_name(rows.column(0))] * len(found), pa.binary()), pa.array([k for k, _ in found], pa.int32()), pa.array([w for _, w in found], pa.binary())], names=["block", "shard", "words"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return map(ask, blocks(batches, 0))  # nothing of a block stays while the next one is gathered

    return docs.select(F.col(text_col).cast("string").alias("text")).mapInArrow(run, "block binary, shard int, words binary")


def packed(docs: DataFrame, text_col: str) -> DataFrame:
    """(block, rows): each block's rows as a compressed Arrow stream."""
    at = docs.columns.index(text_col)

    def pack(rows: pa.RecordBatch) -> pa.RecordBatch:
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, rows.schema, options=pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", 5))) as out:
            out.write_batch(rows)
        give_back()
        return pa.RecordBatch.from_arrays([pa.array([block_name(rows.column(at))], pa.binary()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["block", "rows"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return map(pack, blocks(batches, at))

    return docs.mapInArrow(run, "block binary, rows binary")


def unpacked(words: bytes) -> list[bytes]:
    return zlib.decompress(words).split(b" ")


def distinct_words(asked: pa.Table) -> list[bytes]:
    found = set()
    for words in asked.column("words").to_pylist():
        found.update(unpacked(words))
    return sorted(found)


def portions(tokens: list[bytes]) -> Iterator[tuple[list[bytes], np.ndarray, np.ndarray]]:
    """(some words, their n-grams, index of the word of each) until all words are through."""
    for at in range(0, len(tokens), WORDS_AT_ONCE):
        own = tokens[at : at + WORDS_AT_ONCE]
        yield own, *grams(own)


def distinct_grams(tokens: list[bytes]) -> np.ndarray:
    return np.unique(np.concatenate([np.zeros(0, np.uint64), *(np.unique(key) for _, key, _ in portions(tokens))]))


def word_ratios(asked: DataFrame, table: DataFrame, shards: int) -> DataFrame:
    """(block, shard, found: log ratio of each word, to three digits) of (block, shard, words)."""

    def located(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, seen, unseen = (batch.column(i).to_numpy() for i in range(3))
            part, order = shard(keys.view(np.uint64), shards), np.argsort(keys)
            parts = np.unique(part)
            own = [order[part[order] == k] for k in parts]
            yield pa.RecordBatch.from_arrays([pa.array(parts), *(pa.array([x[k].tobytes() for k in own], pa.binary()) for x in (keys, seen, unseen))], names=["part", "key", "seen", "unseen"])

    def wanted(asked: pa.Table) -> pa.Table:
        keys = distinct_grams(distinct_words(asked))
        home = shard(keys, shards)
        parts = np.unique(home)
        return pa.table([pa.array([asked.column("shard")[0].as_py()] * len(parts), pa.int32()), pa.array(parts, pa.int32()), pa.array([zlib.compress(keys[home == k].tobytes(), 1) for k in parts], pa.binary())], names=["shard", "part", "keys"])

    def answer(wanted: pa.Table, known: pa.Table) -> pa.Table:
        keys, seen, unseen = (np.frombuffer(b"".join(known.column(c).to_pylist()), kind) for c, kind in (("key", np.uint64), ("seen", np.float32), ("unseen", np.float32)))
        order = np.argsort(keys)
        keys, seen, unseen = keys[order], seen[order], unseen[order]
        values = [look_up(np.frombuffer(zlib.decompress(k), np.uint64), keys, seen, unseen).tobytes() for k in wanted.column("keys").to_pylist()]
        return pa.table([wanted.column("shard"), wanted.column("part"), pa.array(values, pa.binary())], names=["shard", "part", "found"])

    def add(asked: pa.Table, answers: pa.Table) -> pa.Table:
        tokens = distinct_words(asked)
        keys = distinct_grams(tokens)
        home, value, ratio = shard(keys, shards), np.zeros(len(keys), np.float32), {}
        for k, found in zip(answers.column("part").to_pylist(), answers.column("found").to_pylist()):
            value[home == k] = np.frombuffer(found, np.float32)
        for own, key, word in portions(tokens):
            ratio.update(zip(own, np.bincount(word, value[np.searchsorted(keys, key)], minlength=len(own)).tolist()))
        words = asked.column("words").to_pylist()
        values = [np.array([ratio[w] for w in unpacked(x)], np.float16).tobytes() for x in words]
        return pa.table([asked.column("block"), asked.column("shard"), pa.array(values, pa.binary())], names=["block", "shard", "found"])

    known = table.select("key", "seen", "unseen").mapInArrow(located, "part int, key binary, seen binary, unseen binary")
    wants = asked.groupBy("shard").applyInArrow(wanted, "shard int, part int, keys binary")
    answers = wants.groupBy("part").cogroup(known.groupBy("part")).applyInArrow(answer, "shard int, part int, found binary")
    return asked.groupBy("shard").cogroup(answers.groupBy("shard")).applyInArrow(add, "block binary, shard int, found binary")


def rated(docs: DataFrame, model: Model, text_col: str, out: dict[str, str], scratch: Scratch | None = None) -> DataFrame:
    """Append the columns ``out``, score and evidence, to each row; same-named columns give way.

    Rows are read twice, once for their words and once to meet the answers, so they have
    to come in the same order: a plan that shuffles is stored first.
    """
    scratch, kept = scratch or Scratch(docs.sparkSession), docs.drop(*out)
    kept = kept.withColumn(text_col, F.col(text_col).cast("string"))
    if any(x in kept._jdf.queryExecution().optimizedPlan().toString() for x in ("Join", "Aggregate", "Repartition", "Window", "Sort", "Sample", "Limit", "Union")):
        kept = scratch.keep(kept, "toxicity-rows")
    schema = StructType(list(kept.schema))
    for name, kind in out.items():
        schema = schema.add(name, kind)
    mean, scale, weights, at = model.mean, model.scale, model.weights, kept.columns.index(text_col)
    (size,) = kept.agg(F.sum(F.octet_length(text_col))).first()
    shards = max(SHARDS, -(-(size or 0) // (4 * BLOCK_BYTES)))
    found = scratch.keep(word_ratios(asked_words(kept, text_col, shards), model.table, shards), "toxicity-words")
    scratch.drop()

    def finish(block: pa.Table, answers: pa.Table) -> pa.Table:
        ratio, done = None, []
        for rows in block.column("rows").to_pylist():  # several only where blocks have equal texts
            (part,) = pa.ipc.open_stream(rows)
            own = Block(part.column(at))
            if ratio is None:
                ratio, home = np.full(len(own.hashes), np.nan), own.homes(shards)
                for k, x in zip(answers.column("shard").to_pylist(), answers.column("found").to_pylist()):
                    ratio[home == k] = np.frombuffer(x, np.float16)
                if np.isnan(ratio).any():
                    raise RuntimeError("rows came in another order the second time; store them before they are scored")
            x = []
            for words in own.parts():
                values, starts = ratio[own.places(words)], words.starts.tolist()
                x += [evidence(values[a:b]) for a, b in zip(starts, starts[1:])]
            x = np.array(x).reshape(-1, N_EVIDENCE)
            score = sigmoid(weights[0] + ((x - mean) / scale) @ weights[1:])
            done.append(pa.RecordBatch.from_arrays([*part.columns, *map(pa.array, (score, *x.T))], names=[*part.schema.names, *out]))
        give_back()
        return pa.Table.from_batches(done)

    return packed(kept, text_col).groupBy("block").cogroup(found.groupBy("block")).applyInArrow(finish, schema)


def fit(labelled: DataFrame, calibration_rows: int = CALIBRATION_ROWS) -> Model:
    """Learn from (id, text, label): counts from most rows, the score from the rest."""
    scratch, parts = Scratch(labelled.sparkSession), 1 << 20
    share = min(parts // CALIBRATION_FOLDS, calibration_rows * parts // max(1, labelled.count()))
    apart = F.pmod(F.xxhash64(F.col("id").cast("string")), F.lit(parts)) < share
    counts = scratch.keep(gram_counts(word_counts(labelled.where(~apart))), "toxicity-grams")
    model = Model(None, np.zeros(1), np.ones(1), np.zeros(1 + N_EVIDENCE))
    if not all(counts.agg(F.sum("toxic"), F.sum("ordinary")).first()):
        model.constant = float(labelled.agg(F.coalesce(F.avg("label"), F.lit(0.0))).first()[0])
        return model
    model.table = scratch.keep(ratio_table(counts), "toxicity-ratios")
    scratch.drop(counts)
    own = Scratch(labelled.sparkSession)
    rows = rated(labelled.where(apart), model, "text", FEATURES, own).select("label", *EVIDENCE).toArrow().to_pandas()
    own.drop_all()
    if rows.label.nunique() < 2:
        model.constant = float(labelled.agg(F.avg("label")).first()[0])
        return model
    model.mean, model.scale, model.weights = logistic(rows[list(EVIDENCE)].to_numpy(float), rows.label.to_numpy(float))
    return model


def score(docs: DataFrame, model: Model, text_col: str = "text", prefix: str = "") -> DataFrame:
    """All columns of ``docs`` with ``score`` and the evidence columns, under ``prefix``."""
    out = {prefix + name: kind for name, kind in FEATURES.items()}
    if model.constant is None:
        return rated(docs, model, text_col, out)
    return docs.drop(*out).select("*", *(F.lit(0.0 if i else model.constant).alias(name) for i, name in enumerate(out)))


def fit_tables(docs: DataFrame, labels: DataFrame) -> Model:
    """Learn ``labels.toxic`` from the rows outside the held-out quarter."""
    return fit(attach(docs, labels, "toxic").where(fold("id", 4) != 2))


def op2_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    scored = score(docs, fit_tables(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return scored.select("doc_id", (fold("doc_id", 4) == 2).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"), *EVIDENCE)
