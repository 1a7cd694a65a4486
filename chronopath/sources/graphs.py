"""Weighted graphs out of the given tables, all as (src, dst, w).

Ids of different kinds are kept apart by arithmetic (2k and 2k + 1) or by hashing
texts to non-negative 60-bit numbers.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window


#: Vectors of a label that a task holds while all of the label pass, and vectors that pass at once; both bound memory only.
PART_VECTORS, VECTORS_AT_ONCE = 8192, 512


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def simple(pairs: DataFrame) -> DataFrame:
    """No self-loops, the smallest weight of a pair."""
    return pairs.where("src <> dst").groupBy("src", "dst").agg(F.min("w").cast("double").alias("w"))


def both_ways(pairs: DataFrame) -> DataFrame:
    return pairs.unionByName(pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))


def text_id(value: str | Column, salt: str) -> Column:
    """A number for a text: the first 15 hexadecimal digits of its MD5."""
    col = F.col(value) if isinstance(value, str) else value
    return F.conv(F.substring(F.md5(F.concat(F.lit(salt), col).cast("binary")), 1, 15), 16, 10).cast("long")


def basket(spark, sf_dir):
    """Part to the next part of the same order; the quantity of the first line."""
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_quantity")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity")
    return simple(lines.select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(order).alias("dst"), F.col("l_quantity").alias("w")).where("dst is not null"))


def trade(spark, sf_dir):
    """Customers (2c) and suppliers (2s + 1) that meet in an order line, both ways."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_quantity")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    met = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return simple(both_ways(met.select((2 * F.col("o_custkey")).alias("src"), (2 * F.col("l_suppkey") + 1).alias("dst"), F.col("l_quantity").alias("w"))))


def visit(spark, sf_dir):
    """User of an event to the user of the next one of the same kind and day; the window stays partitioned."""
    order = Window.partitionBy("event_type", F.to_date("ts")).orderBy("ts", "event_id")
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value")
    return simple(events.select(F.col("user_id").alias("src"), F.lead("user_id").over(order).alias("dst"), F.greatest(F.lit(1), F.ceil("value")).alias("w")).where("dst is not null"))


def visit_timed(spark, sf_dir):
    """As ``visit``, a row for each pair and day number since the first day."""
    order = Window.partitionBy("event_type", F.to_date("ts")).orderBy("ts", "event_id")
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value")
    rows = events.select(F.col("user_id").alias("src"), F.lead("user_id").over(order).alias("dst"), F.greatest(F.lit(1), F.ceil("value")).alias("w"), F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date")).alias("at"))
    return rows.where("dst is not null and src <> dst").groupBy("src", "dst", "at").agg(F.min("w").cast("double").alias("w"))


def supply(spark, sf_dir):
    """Parts (2p) and suppliers (2s + 1), both ways; the price in thousands."""
    lines = table(spark, sf_dir, "lineitem")
    return simple(both_ways(lines.select((2 * F.col("l_partkey")).alias("src"), (2 * F.col("l_suppkey") + 1).alias("dst"), F.floor(F.col("l_extendedprice") / 1000).alias("w"))))


def _as_matrix(column: pa.Array) -> np.ndarray:
    """Vectors as rows of doubles; what a vector lacks is NaN."""
    column = pc.fill_null(column, pa.scalar([], column.type)) if column.null_count else column
    sizes, flat = np.asarray(pc.list_value_length(column)), column.flatten().cast(pa.float64())
    out = np.full((len(column), int(sizes.max(initial=0))), np.nan)
    out[np.arange(out.shape[1]) < sizes[:, None]] = flat.to_numpy(zero_copy_only=False)
    return out


def _joined(parts: list[np.ndarray]) -> np.ndarray:
    width = max(x.shape[1] for x in parts)
    return np.concatenate([np.pad(x, ((0, 0), (0, width - x.shape[1])), constant_values=np.nan) for x in parts])


class _Nearest:
    """The ``k`` nearest so far to some vectors, by squared distance to 6 digits, then by id."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, k: int):
        self.ids, self.vectors, self.k = ids, vectors, k
        self.whole = np.isfinite(vectors).all()
        self.squares = (vectors * vectors).sum(axis=1)
        self.found = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)]  # place here, id there, squared distance (NaN: none)
        self.worst = np.full(len(ids), np.inf)

    def meet(self, ids: np.ndarray, vectors: np.ndarray) -> None:
        width = max(vectors.shape[1], self.vectors.shape[1])
        mine, other = (np.pad(x, ((0, 0), (0, width - x.shape[1])), constant_values=np.nan) for x in (self.vectors, vectors))
        apart = self.ids[:, None] != ids[None, :]
        if self.whole and self.vectors.shape[1] == vectors.shape[1] and np.isfinite(vectors).all():
            # Candidates by a matrix product, with room for its error and the rounding.
            squares = (other * other).sum(axis=1)
            far = self.squares[:, None] + squares[None, :] - 2 * (mine @ other.T)
            room = 3e-6 + 1e-12 * (self.squares + squares.max(initial=0))
            far[~apart] = np.inf
            limit = np.minimum(self.worst, np.partition(far, self.k - 1, axis=1)[:, self.k - 1] if far.shape[1] > self.k else np.inf)
            apart &= far <= (limit + room)[:, None]
        at, there = np.nonzero(apart)
        exact, seen = np.zeros(len(at)), np.zeros(len(at), bool)
        for j in range(width):  # in the order of the SQL's sum, so with its rounding
            step = mine[at, j] - other[there, j]
            step *= step
            known = ~np.isnan(step)
            exact[known] += step[known]
            seen |= known
        exact[~seen] = np.nan
        at, ids, exact = (np.concatenate(x) for x in zip(self.found, (at, ids[there], exact)))
        order = np.lexsort((ids, np.round(exact, 6), at))  # NaN comes last
        at, ids, exact = at[order], ids[order], exact[order]
        starts = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]])[: len(at)])
        place = np.arange(len(at)) - np.repeat(starts, np.diff(np.append(starts, len(at))))
        last = place == self.k - 1
        self.worst[at[last]] = np.where(np.isnan(exact[last]), np.inf, exact[last])
        kept = place < self.k
        self.found = [at[kept], ids[kept], exact[kept]]

    def batch(self) -> pa.RecordBatch:
        at, ids, far = self.found
        return pa.RecordBatch.from_arrays([pa.array(self.ids[at]), pa.array(ids), pa.array(far, mask=np.isnan(far))], names=["src", "dst", "far"])


def _nearest(k: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(src, dst, far) of rows (label, part, side, vec_id, embedding) in order: the vectors of side 0 of a part meet those of side 1 as they pass."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, mine, near = None, [], None
        for batch in batches:
            label, part, side = (batch.column(c).to_numpy() for c in range(3))
            cuts = np.flatnonzero((label[1:] != label[:-1]) | (part[1:] != part[:-1]) | (side[1:] != side[:-1])) + 1
            for a, b in zip([0, *cuts], [*cuts, batch.num_rows]):
                if (label[a], part[a]) != key:
                    if near:
                        yield near.batch()
                    key, mine, near = (label[a], part[a]), [], None
                ids, vectors = batch.column(3)[a:b].to_numpy(), _as_matrix(batch.column(4)[a:b])
                if side[a] == 0:
                    mine.append((ids, vectors))
                elif mine or near:
                    if not near:
                        near, mine = _Nearest(np.concatenate([x for x, _ in mine]), _joined([x for _, x in mine]), k), []
                    for at in range(0, b - a, VECTORS_AT_ONCE):
                        near.meet(ids[at : at + VECTORS_AT_ONCE], vectors[at : at + VECTORS_AT_ONCE])
        if near:
            yield near.batch()

    return go


def knn(spark, sf_dir, k: int = 3):
    """The k nearest vectors of the same label by squared distance (label buckets bound the pairs).

    A label's vectors are dealt to parts, all others of the label pass each part, and matrix products find candidates
    for exact distances. Of equal vectors only the first ``k + 1`` ids pass, since no other can be among the k nearest."""
    vectors = table(spark, sf_dir, "embeddings").where("label is not null and vec_id is not null").select("label", F.col("vec_id").cast("long").alias("vec_id"), "embedding")
    parts = vectors.groupBy("label").agg(F.ceil(F.count("*") / PART_VECTORS).cast("int").alias("parts"))
    mine = vectors.join(parts, "label").select("label", F.expr("cast(pmod(xxhash64(vec_id), parts) as int)").alias("part"), F.lit(0).alias("side"), "vec_id", "embedding")
    equal = Window.partitionBy("label", "embedding").orderBy("vec_id")
    first = vectors.withColumn("r", F.dense_rank().over(equal)).where(F.col("r") <= k + 1).drop("r")
    passing = first.join(parts, "label").select("label", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(1).alias("side"), "vec_id", "embedding")
    dealt = mine.unionByName(passing).repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "label", "part").sortWithinPartitions("label", "part", "side")
    pairs = dealt.mapInArrow(_nearest(k), "src long, dst long, far double").select("src", "dst", F.round("far", 6).alias("d"))
    near = pairs.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.asc_nulls_last("d"), "dst"))).where(F.col("r") <= k)
    return near.select("src", "dst", (1 + F.col("d")).alias("w"))


def geo(spark, sf_dir):
    """Region to nation to customer and supplier; weight 1. Regions are negative, nations under 1000."""
    nation = table(spark, sf_dir, "nation").select((-1 - F.col("n_regionkey").cast("long")).alias("src"), F.col("n_nationkey").cast("long").alias("dst"))
    customer = table(spark, sf_dir, "customer").select(F.col("c_nationkey").cast("long").alias("src"), (1000 + 2 * F.col("c_custkey")).alias("dst"))
    supplier = table(spark, sf_dir, "supplier").select(F.col("s_nationkey").cast("long").alias("src"), (1001 + 2 * F.col("s_suppkey")).alias("dst"))
    return nation.unionByName(customer).unionByName(supplier).withColumn("w", F.lit(1.0))


def linkhost(spark, sf_dir):
    """Host of a page to the paths it links; weight 1."""
    pages = table(spark, sf_dir, "pages").select(F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"), F.explode(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), 1)).alias("path"))
    return pages.select(text_id("host", "h").alias("src"), text_id("path", "p").alias("dst"), F.lit(1.0).alias("w")).distinct()


def reply(spark, sf_dir):
    """Turn to the next turn of a conversation; weight by the length of the text."""
    order = Window.partitionBy("conv_id").orderBy("turn")
    turns = table(spark, sf_dir, "conversations")
    at = (1000 * F.col("conv_id") + F.col("turn")).cast("long")
    rows = turns.select(at.alias("src"), F.lead(at).over(order).alias("dst"), (1 + F.floor(F.coalesce(F.char_length("text"), F.lit(0)) / 100)).alias("w"))
    return simple(rows.where("dst is not null"))


def curated(spark, sf_dir):
    """Source (negative ids) to its documents labelled good and not toxic; weight 1."""
    good = table(spark, sf_dir, "labels").where("quality = 1 and toxic = 0").select("doc_id")
    docs = table(spark, sf_dir, "documents").select("doc_id", "source")
    return docs.join(good, "doc_id").select((-1 - text_id("source", "s")).alias("src"), F.col("doc_id").alias("dst"), F.lit(1.0).alias("w")).distinct()


LETTERS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Bytes of a run's second hash, runs packed at once and words remembered in a worker (both bound memory only), and input a bucket of runs is meant for.
RUN_CHECK, RUNS_AT_ONCE, VOCABULARY, BUCKET_BYTES = 3, 1 << 21, 1 << 20, 4 << 20


def _grams(spark, sf_dir, name, key, n=5):
    """(key, digest) of the distinct runs of ``n`` words, A-Z in lower case; texts of fewer words have none."""
    words = F.regexp_extract_all(F.translate("text", LETTERS, LETTERS.lower()), F.lit(r"[^ \t\n\x0B\f\r]+"), 0)
    rows = table(spark, sf_dir, name).select(F.col(key).alias("id"), words.alias("words")).where(F.size("words") >= n)
    digests = F.transform(F.sequence(F.lit(1), F.size("words") - n + 1), lambda i: F.md5(F.concat_ws(" ", F.slice("words", i, n)).cast("binary")))
    return rows.select("id", F.explode(F.array_distinct(digests)).alias("h")).distinct()


def _planes(values: np.ndarray, width: int) -> bytes:
    """The ``width`` low bytes of 64-bit numbers, all highest bytes first, so that runs of equal bytes compress."""
    return values.astype(">u8").view(np.uint8).reshape(-1, 8)[:, 8 - width :].T.tobytes()


def _numbers(planes: np.ndarray, width: int) -> np.ndarray:
    out = np.zeros((planes.size // width, 8), np.uint8)
    out[:, 8 - width :] = planes.reshape(width, -1).T
    return out.view(">u8").ravel().astype(np.uint64)


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(29))


class _Vocabulary(dict):
    """Number of a word, with 128 bits of its digest in a row of ``digests``."""

    def __init__(self):
        self.digests = np.zeros((1 << 12, 2), np.uint64)

    def __missing__(self, word: bytes) -> int:
        self[word] = at = len(self)
        if at == len(self.digests):
            self.digests = np.concatenate([self.digests, np.zeros_like(self.digests)])
        self.digests[at] = np.frombuffer(hashlib.blake2b(word, digest_size=16).digest(), np.uint64)
        return at


def _packed_runs(bits: int, n: int = 5) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """(bucket, runs) of (id, text): two hashes of each distinct run of ``n`` words of a text and its id, as bytes by the first ``bits`` of the first hash."""

    def sent(parts: list[tuple]) -> Iterator[pa.RecordBatch]:
        ids, h, g = (np.concatenate([x[k] for x in parts]) for k in range(3))
        order = np.argsort(h, kind="stable")  # rows of a document stay together
        ids, h, g = ids[order], h[order], g[order]
        new = np.concatenate([[True], (h[1:] != h[:-1]) | (g[1:] != g[:-1]) | (ids[1:] != ids[:-1])])
        ids, h, g = ids[new], h[new], g[new]
        bucket = (h >> np.uint64(64 - bits)).astype(np.int32)
        starts = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]]))
        ends = np.append(starts[1:], len(h))
        for at in range(0, len(starts), 512):
            blobs = [_planes(h[a:b], 8) + _planes(g[a:b], RUN_CHECK) + _planes(ids[a:b], 8) for a, b in zip(starts[at : at + 512], ends[at : at + 512])]
            yield pa.RecordBatch.from_arrays([pa.array(bucket[starts[at : at + 512]]), pa.array(blobs, pa.binary())], names=["bucket", "runs"])

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, parts, held = _Vocabulary(), [], 0
        for batch in batches:
            for id_, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                words = (text.as_py() or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z only, and the six white spaces of the SQL
                m = len(words) - n + 1
                if m < 1:
                    continue
                if len(known) > VOCABULARY:
                    known = _Vocabulary()
                at = np.fromiter(map(known.__getitem__, words), np.int64, len(words))
                h, g = np.zeros(m, np.uint64), np.ones(m, np.uint64)
                digests = known.digests[at]
                for k in range(n):
                    h, g = _mixed(h * np.uint64(3) + digests[k : k + m, 0]), _mixed(g * np.uint64(3) + digests[k : k + m, 1])
                parts.append((np.full(m, id_, np.int64), h, g & np.uint64((1 << 8 * RUN_CHECK) - 1)))
                held += m
                if held >= RUNS_AT_ONCE:
                    yield from sent(parts)
                    parts, held = [], 0
        if held:
            yield from sent(parts)

    return go


def _first_pairs(group: pa.Table) -> pa.Table:
    """(src, dst, n) of one bucket: the first document of each run with the others, and in how many runs."""
    parts = []
    for blob in group.column("runs"):
        body = np.frombuffer(blob.as_py(), np.uint8)
        m = body.size // (16 + RUN_CHECK)
        parts.append((_numbers(body[: 8 * m], 8), _numbers(body[8 * m : (8 + RUN_CHECK) * m], RUN_CHECK), _numbers(body[(8 + RUN_CHECK) * m :], 8).view(np.int64)))
    h, g, ids = (np.concatenate([x[k] for x in parts]) for k in range(3))
    order = np.lexsort((ids, g, h))
    h, g, ids = h[order], g[order], ids[order]
    run = np.concatenate([[True], (h[1:] != h[:-1]) | (g[1:] != g[:-1])])
    new = run | np.concatenate([[True], ids[1:] != ids[:-1]])
    first = ids[np.flatnonzero(run)][np.cumsum(run) - 1]
    other = new & (ids != first)
    src, dst = first[other], ids[other]
    order = np.lexsort((dst, src))
    src, dst = src[order], dst[order]
    starts = np.flatnonzero(np.concatenate([[True], (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])])[: len(src)])
    return pa.table({"src": src[starts], "dst": dst[starts], "n": np.diff(np.append(starts, len(src)))})


def lookalike(spark, sf_dir):
    """Document to the first document with five words in a row in common, both ways (a star for each run, not all pairs); weight 1 + shared runs.

    Runs are known by 88 bits of hashes and move once, packed, to where those of a bucket meet."""
    docs = table(spark, sf_dir, "documents")
    size = int(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    bits = min(20, max(12, (size // BUCKET_BYTES).bit_length()))
    docs = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("id"), F.col("text").cast("string"))
    packed = docs.mapInArrow(_packed_runs(bits), "bucket int, runs binary")
    pairs = packed.groupBy("bucket").applyInArrow(_first_pairs, "src long, dst long, n long")
    pairs = pairs.groupBy("src", "dst").agg((1 + F.sum("n")).cast("double").alias("w"))
    ways = F.array(F.struct("src", "dst"), F.struct(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return pairs.select(F.explode(ways).alias("e"), "w").select("e.src", "e.dst", "w")


def quiz(spark, sf_dir):
    """Benchmark item (negative ids) to the documents that hold five of its words in a row; weight 1."""
    items = _grams(spark, sf_dir, "benchmark", "item_id").select((-1 - F.col("id")).alias("src"), "h")
    docs = _grams(spark, sf_dir, "documents", "doc_id").select(F.col("id").alias("dst"), "h")
    return docs.join(items, "h").select("src", "dst", F.lit(1.0).alias("w")).distinct()


GRAPHS = {f.__name__: f for f in (basket, trade, visit, supply, knn, geo, linkhost, reply, curated, lookalike, quiz)}
