"""Shared helpers: scratch tables in the cluster's shared folder, word and token codecs.

Words follow one rule everywhere: maximal runs of characters other than space
and the control characters 9-13. ``bytes.split()`` splits on exactly that set,
so all word work happens on UTF-8 bytes.
"""

from __future__ import annotations

import contextlib
import ctypes
import gc
import itertools
import os
import uuid
from array import array
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Observation, SparkSession

#: Text handled together in a Python worker, and entries a worker's memo may hold
#: before it starts afresh. Both bound memory only; results do not depend on them.
BATCH_BYTES = 4 << 20
MEMO_ENTRIES = 400_000


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, or the one set on the context."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        option = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = option.get() if option.isDefined() else None
    if not found:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/chronopath-scratch"  # one machine: any folder is shared
    return found.rstrip("/")


class Scratch:
    """Parquet tables under the shared folder: they cut lineage and outlive lost executors."""

    def __init__(self, spark: SparkSession):
        self.spark, self.root, self.paths = spark, shared_dir(spark), {}

    def keep(self, df: DataFrame, name: str = "t") -> DataFrame:
        path = f"{self.root}/chronopath-{name}-{uuid.uuid4().hex}"
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(out)] = (path, out)
        return out

    def observed(self, df: DataFrame, name: str, **measures: Column) -> tuple[DataFrame, dict]:
        """The stored table, and numbers taken while it was written."""
        observation = Observation()
        return self.keep(df.observe(observation, *(c.alias(k) for k, c in measures.items())), name), observation.get

    def drop(self, *frames: DataFrame) -> None:
        """Delete tables that no later result reads; Spark then deletes the shuffle files behind tables already stored."""
        jvm, conf = self.spark._jvm, self.spark.sparkContext._jsc.hadoopConfiguration()
        for df in frames:
            path = jvm.org.apache.hadoop.fs.Path(self.paths.pop(id(df))[0])
            path.getFileSystem(conf).delete(path, True)
        gc.collect()  # plans that Python no longer reaches hold shuffle files too
        jvm.System.gc()

    def drop_all(self) -> None:
        self.drop(*(df for _, df in list(self.paths.values())))


def give_back() -> None:
    """Memory that Python has freed goes back to the system: workers stay after their tasks, beside those at work."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError, OSError):  # only glibc has it
        ctypes.CDLL(None).malloc_trim(0)


def slices(batches: Iterable[pa.RecordBatch], text: str = "text", limit: int = BATCH_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches so that one holds about ``limit`` bytes of text; a longer text stands alone."""
    for batch in batches:
        col = batch.column(batch.schema.get_field_index(text))
        sizes = np.asarray(pc.fill_null(pc.binary_length(col), 0), dtype=np.int64)
        ends, at = np.cumsum(sizes), 0
        while at < batch.num_rows:
            base = ends[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(ends, base + limit, "right")))
            yield batch.slice(at, to - at)
            at = to


def words(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").split() if text else []


def lower_words(text: str | None) -> list[bytes]:
    """Words with A-Z lowered (``bytes.lower`` touches ASCII only)."""
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []


class WordHash(dict):
    """64-bit hash of a word, remembered while the worker sees it again."""

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= MEMO_ENTRIES:
            self.clear()
        self[word] = found = xxhash.xxh3_64_intdigest(word)
        return found

    def array(self, tokens: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, tokens), np.uint64, len(tokens))


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of uint64 (two multiply-xorshift rounds)."""
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


_BASE = np.uint64(0x9E3779B97F4A7C15)
_INVERSE = np.uint64(pow(int(_BASE), -1, 1 << 64))


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first n + 1 powers of the base and of its inverse, modulo 2**64."""
    up, down = np.full(n + 1, _BASE), np.full(n + 1, _INVERSE)
    up[0] = down[0] = 1
    return np.multiply.accumulate(up), np.multiply.accumulate(down)


class Rolling:
    """Polynomial hashes of all windows of a sequence, modulo 2**64."""

    def __init__(self, tokens: np.ndarray):
        up, self.down = powers(len(tokens))
        self.prefix = np.zeros(len(tokens) + 1, np.uint64)
        np.cumsum(tokens * up[:-1], out=self.prefix[1:])

    def spans(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        return mix((self.prefix[ends] - self.prefix[starts]) * self.down[starts])

    def windows(self, size: int) -> np.ndarray:
        n = max(0, len(self.prefix) - size)
        return mix((self.prefix[size:] - self.prefix[:n]) * self.down[:n]) if n else np.zeros(0, np.uint64)


#: Bytes of text hashed together, and the longest word hashed by the polynomial; longer ones go through a library hash.
PIECE_BYTES, LONG_WORD = 1 << 18, 255
_SPACE = np.zeros(256, bool)
_SPACE[[32, *range(9, 14)]] = True
_AS_IS = np.arange(1, 257, dtype=np.uint64)
_LOWERED = _AS_IS.copy()
_LOWERED[65:91] += np.uint64(32)


class WordColumn:
    """The words of an Arrow column of texts (null: none) as 64-bit hashes, without a Python object for each.

    ``hashes`` has all words in order, ``starts`` where each text's words begin (one entry
    more than texts), ``spans`` the bytes of each word in ``data``.
    """

    def __init__(self, column: pa.Array, lower: bool = False):
        column = pc.fill_null(column, "").cast(pa.large_string())
        _, offsets, data = column.buffers()
        offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
        self.data = (np.frombuffer(data, np.uint8) if data else np.zeros(0, np.uint8))[offsets[0] : offsets[-1]]
        self.offsets, body = offsets - offsets[0], self.data
        inside = ~_SPACE[body]
        edges = self.offsets[1:-1][(self.offsets[1:-1] > 0) & (self.offsets[1:-1] < len(body))]
        first, before = inside.copy(), inside[edges - 1]
        first[1:] &= ~inside[:-1]
        first[edges] = inside[edges]
        begin = np.flatnonzero(first)
        inside[:-1] &= ~inside[1:]  # from here on the last bytes of words
        inside[edges - 1] = before
        end = np.flatnonzero(inside)
        end += 1
        del inside, first
        self.spans, self.starts = (begin, end), np.searchsorted(begin, self.offsets)
        self.hashes, values, at = np.empty(len(begin), np.uint64), _LOWERED if lower else _AS_IS, 0
        up, down = powers(min(PIECE_BYTES, len(body)))
        while at < len(begin):
            to = max(at + 1, int(np.searchsorted(end, begin[at] + PIECE_BYTES, "right")))
            low, high = begin[at], end[to - 1]
            if high - low <= PIECE_BYTES:  # else a single long word, hashed below
                sums = np.zeros(high - low + 1, np.uint64)
                np.cumsum(values[body[low:high]] * up[: high - low], out=sums[1:])
                self.hashes[at:to] = mix((sums[end[at:to] - low] - sums[begin[at:to] - low]) * down[begin[at:to] - low])
            at = to
        for k in np.flatnonzero(end - begin > LONG_WORD):
            import xxhash

            word = body[begin[k] : end[k]].tobytes()
            self.hashes[k] = xxhash.xxh3_64_intdigest(word.lower() if lower else word)

    @property
    def sizes(self) -> np.ndarray:
        return np.diff(self.starts)


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    """Place of a public vocabulary file on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


#: Kinds of bytes for cutting a text. Letters are those whose class no edition of Unicode changed: A-Z, a-z and
#: two bytes each of U+00C0 to U+023F (but for two signs) and U+0400 to U+047F. TAIL: not the first byte of its character.
OTHER, LETTER, DIGIT, SIGN, SPACE, FEED, APOSTROPHE, TAIL = range(8)
_KIND = np.zeros(256, np.uint8)
_KIND[33:127], _KIND[48:58], _KIND[128:192] = SIGN, DIGIT, TAIL
_KIND[[*range(65, 91), *range(97, 123), *range(0xC3, 0xC9), 0xD0, 0xD1]] = LETTER
_KIND[[32, 10, 39]] = SPACE, FEED, APOSTROPHE
_BEFORE, _BETWEEN = np.zeros(64, bool), np.zeros(64, bool)  # by the kinds of two neighbours: cut before the first, between both
for _a, _b in ((LETTER, DIGIT), (LETTER, SIGN), (LETTER, APOSTROPHE), (DIGIT, LETTER), (DIGIT, SIGN), (DIGIT, APOSTROPHE), (SIGN, LETTER), (SIGN, DIGIT)):
    _BETWEEN[8 * _a + _b] = True
for _b in (LETTER, DIGIT, SIGN, APOSTROPHE):
    _BEFORE[[8 * SPACE + _b, 8 * FEED + _b]] = _BETWEEN[8 * FEED + _b] = True
_UNSURE = np.zeros(64, bool)
_UNSURE[[8 * SPACE + OTHER, 8 * FEED + OTHER]] = True
#: Longest part of a text, in bytes, whose ids are remembered.
MEMO_BYTES = 64


def _kinds(body: np.ndarray) -> np.ndarray:
    kind = _KIND[body]
    tail = np.flatnonzero(kind == TAIL)
    lead = body[tail - 1]
    letter = (_KIND[lead] == LETTER) & (lead >= 128) & ~((lead == 0xC3) & ((body[tail] == 0x97) | (body[tail] == 0xB7)))
    kind[tail] = letter  # OTHER or LETTER
    kind[tail[~letter] - 1] = OTHER
    return kind


def _white(body: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Whether white space, in a sense wider than Python's, may begin at these bytes."""
    a, b, c = (body[np.minimum(at + k, len(body) - 1)] for k in range(3))
    return (a <= 32) | (a == 0xE1) | ((a == 0xC2) & ((b == 0x85) | (b == 0xA0))) | ((a == 0xE2) & ((b == 0x81) | ((b == 0x80) & ((c <= 0x8D) | (c == 0xA8) | (c == 0xA9) | (c == 0xAF))))) | ((a == 0xE3) & (b == 0x80) & (c == 0x80))


class BpeBytes(dict):
    """Ids of texts by the ``tokenizers`` library, without special tokens added.

    The vocabulary's split pattern always cuts where a run of letters or digits ends, between
    other signs than an apostrophe and a letter or digit, and before a space or line feed that
    a character other than white space follows: whatever stands before it, a run of white space
    gives up its last character there (a line feed then stands alone). What a part between such
    places is split into does not depend on its neighbours, so the parts of a whole block of texts
    are told apart by Arrow, each is encoded once, and the ids of short ones are remembered.
    White space is taken in a wider sense and letters in a narrower one than the library's, so no
    cut is made that the library would not make. A part that is a single run goes to the library's
    model, others to the library as they are, as do whole texts with the string of a special
    token, which the library looks for first.
    """

    def __init__(self, path: str | None = None):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path or tokenizer_path())
        self.model, self.older = self.library.model, {}
        self.special = [t.content for t in self.library.get_added_tokens_decoder().values()]
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that stand for themselves; the others follow behind 255
        self.shown = np.arange(256, dtype="<u4")
        self.shown[sorted({*range(256)} - {*shown})] = np.arange(256, 512 - len(shown))

    @staticmethod
    def cut(body: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Where the parts of texts begin, and the end of all; ``offsets``: where the texts do."""
        inner = offsets[(offsets > 0) & (offsets < len(body))]
        kind = _kinds(body)
        pair = kind[:-1] * 8 + kind[1:]
        pair[inner - 1] = 0  # another text is no neighbour
        unsure = np.flatnonzero(_UNSURE[pair])
        unsure = unsure[~_white(body, unsure + 1)]
        cut = np.zeros(len(body) + 1, bool)
        cut[: len(pair)] = _BEFORE[pair]
        cut[1 : len(pair) + 1] |= _BETWEEN[pair]
        cut[unsure] = cut[unsure[kind[unsure] == FEED] + 1] = True
        cut[offsets] = True
        return np.flatnonzero(cut)

    def parts(self, body: np.ndarray, starts: np.ndarray) -> list[bytes]:
        """The packed ids of parts that stand one after another."""
        if len(self) >= MEMO_ENTRIES // 2:
            self.older = dict(self)  # what was seen since the last time; parts still in use come back from there
            self.clear()
        raw, bounds = body.tobytes(), starts.tolist()
        keys = [raw[a:b] for a, b in itertools.pairwise(bounds)]
        found = list(map(self.get, keys))
        if missing := [k for k, ids in enumerate(found) if ids is None]:
            kind = _kinds(body)
            odd = (kind == OTHER) | (kind >= SPACE)
            odd[starts[:-1]] &= (kind[starts[:-1]] != SPACE) & (kind[starts[:-1]] != FEED)
            odd, shown = np.logical_or.reduceat(odd, starts[:-1]).tolist(), self.shown[body].tobytes().decode("utf-32-le")
            for k in missing:
                ids = self.older.get(keys[k])
                if ids is None:
                    ids = array("I", self.library.encode(keys[k].decode(), add_special_tokens=False).ids if odd[k] else [t.id for t in self.model.tokenize(shown[bounds[k] : bounds[k + 1]])]).tobytes()
                found[k] = ids
                if len(keys[k]) <= MEMO_BYTES:
                    self[keys[k]] = ids
        return found

    def column(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """The ids of an Arrow column of texts (null: none) as uint32, and where each text's begin (one entry more than texts)."""
        texts = pc.fill_null(texts, "").cast(pa.large_string())
        texts.validate(full=True)
        for s in self.special:
            if len(whole := np.flatnonzero(np.asarray(pc.match_substring(texts, s)))):
                ids, starts = self.column(pc.if_else(pc.match_substring(texts, s), "", texts))
                apart = [self.library.encode(texts[k].as_py(), add_special_tokens=False).ids for k in whole.tolist()]
                sizes = np.zeros(len(texts) + 1, np.int64)
                sizes[whole + 1] = [len(x) for x in apart]
                ids = np.insert(ids, np.repeat(starts[whole], sizes[whole + 1]), np.array([x for own in apart for x in own], np.uint32))
                return ids, starts + np.cumsum(sizes)
        _, offsets, data = texts.buffers()
        offsets = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1]
        body = (np.frombuffer(data, np.uint8) if data else np.zeros(0, np.uint8))[offsets[0] : offsets[-1]]
        offsets = offsets - offsets[0]
        if not len(body):
            return np.zeros(0, np.uint32), np.zeros(len(texts) + 1, np.int64)
        at = self.cut(body, offsets)
        coded = pa.Array.from_buffers(pa.large_binary(), len(at) - 1, [None, pa.py_buffer(at), pa.py_buffer(np.ascontiguousarray(body))]).dictionary_encode()
        _, starts, different = coded.dictionary.buffers()
        starts = np.frombuffer(starts, np.int64)[: len(coded.dictionary) + 1]
        found = self.parts(np.frombuffer(different, np.uint8)[: starts[-1]], starts)
        sizes, which = np.fromiter(map(len, found), np.int64, len(found)) // 4, np.asarray(coded.indices)
        ends = np.cumsum(sizes[which])
        ids = np.frombuffer(b"".join(found), np.uint32)[np.arange(ends[-1]) + np.repeat((np.cumsum(sizes) - sizes)[which] - ends + sizes[which], sizes[which])]
        return ids, np.append(0, ends)[np.searchsorted(at, offsets)]

    def encode(self, text: str | None) -> bytes:
        """The ids of one text as packed little-endian uint32."""
        return self.column(pa.array([text], pa.large_string()))[0].tobytes()


_BPE: dict[str | None, BpeBytes] = {}


def bpe(path: str | None = None) -> BpeBytes:
    """One encoder a worker process."""
    if path not in _BPE:
        _BPE[path] = BpeBytes(path)
    return _BPE[path]
