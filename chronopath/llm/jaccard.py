"""Near duplicates: a join on the Jaccard similarity of word shingles.

Documents are sets of shingle hashes; documents of equal sets are one class and go on as
one set. Sets that overlap in ``o`` shingles share at least l of the first ``n - o + l``
in any fixed order of all shingles. The order here is by how often shingles occur that
fall into the same of 2^``BUCKET_BITS`` hash buckets, rare ones first, then by hash:
these counts cover the whole table, have a fixed size whatever the input, and only steer
the work, since any order gives the same links.

Each set lengthens its prefix as far as its estimated candidate cost falls (``LEVELS``
steps): of (occurrences met) x (1 + verification / l), the second factor being a bound
on the candidates that share l of them. Prefix shingles of one set only cannot match
and go. Sets meet at the shingles of their shortest prefixes, where their sizes and the
place of the shingle in both leave enough for the overlap that the two sizes ask for
(``reach``); a shingle of two sets that cannot meet there goes too. A pair then has to share
k of the first ``n - o + k`` for every k up to the smaller l of the two, and parity maps
of the whole sets must not rule it out, before it is verified on the whole sets.

Shingles of at most ``FEW_SETS`` sets have all their pairs compared at once and are done
with. Larger groups would make a square number of pairs, so in rounds each
shingle first ties its sets to two of their number, others in each round, by verified
pairs; sets that links connect need no further comparison among each other, and a shingle
whose sets are all connected leaves the rounds.
All remaining pairs between different components then meet, once where their heads
(the first ``HEAD`` shared shingles) have one in common, so no link is lost.

Edge cases: a text with fewer words than a shingle has its whole sequence as one;
texts without words, null texts and rows without an id have no links (their
component is their own id); rows of one id with different texts are different
documents, each linked by its own text; repeated rows are in one class; an empty table
gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from chronopath.llm.common import Rolling, Scratch, WordColumn, mix, slices
from chronopath.llm.components import components

LEVELS, VERIFY_COST = 4, 20
#: Size of the table of counts that orders shingles, and of a set's parity map: two sets differ in at least as many members as their maps differ in bits.
BUCKET_BITS, MAP_BITS = 24, 512
#: Buckets whose counts travel in one row.
BLOCK = 4096
#: Rounds of ties before the remaining pairs are listed (sooner if those are at most so many times the rows of all shared shingles, or fall too slowly),
#: and shared shingles by which such pairs are told apart.
TIE_ROUNDS, FEW_PAIRS, HEAD = 4, 4, 16
#: Sets of a shingle that are all compared at once, without rounds: at most 3.5 pairs a row.
FEW_SETS = 8
#: Bits of the map of ids whose texts are wanted; a fuller map lets more texts through to the join and drops none.
WANTED_BITS = 26
#: Text worked on at once in a Python worker; bounds memory only.
WORK_BYTES = 1 << 20
_SHORT = np.uint64(0xA0761D6478BD642F)


def overlap(n, num: int, den: int):
    """Smallest overlap of a set of n with a partner at the threshold (for ints, arrays or columns)."""
    return F.floor((n * num + den - 1) / den).cast("int") if isinstance(n, Column) else (n * num + den - 1) // den


def reach(n: Column, at: Column, num: int, den: int) -> Column:
    """Size of the largest partner of a set of n that can have its first common shingle at place ``at`` (from 0) of this set's order.

    ``n - at`` shingles from there on have to cover the overlap, which is at least num / (num + den) of both sizes together.
    """
    return F.floor((n.cast("long") * den - at.cast("long") * (num + den)) / num).cast("long")


def shingles(column: pa.Array, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of the shingles of all texts in order, where each text's begin: one entry more than texts)."""
    words = WordColumn(column, lower=True)
    rolling, sizes = Rolling(words.hashes), words.sizes
    windows = rolling.windows(size)
    counts = np.where(sizes >= size, sizes - size + 1, (sizes > 0).astype(np.int64))
    ends = np.cumsum(counts)
    out = np.empty(int(counts.sum()), np.uint64)
    long = np.flatnonzero(sizes >= size)
    if len(long):
        n = counts[long]
        step = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n)
        out[np.repeat(ends[long] - n, n) + step] = windows[np.repeat(words.starts[long], n) + step]
    short = np.flatnonzero((sizes > 0) & (sizes < size))
    out[ends[short] - 1] = mix(rolling.spans(words.starts[short], words.starts[short + 1]) ^ _SHORT)
    return out, np.concatenate([[0], ends])


def shingle_sets(column: pa.Array, size: int) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text."""
    found, starts = shingles(column, size)
    return [np.unique(found[a:b]) for a, b in zip(starts[:-1].tolist(), starts[1:].tolist())]


def digest(members: np.ndarray) -> bytes:
    return hashlib.blake2b(members.tobytes(), digest_size=16).digest()


def _coded(counts: np.ndarray) -> np.ndarray:
    """Counts in a byte each: up to 127 as they are, larger ones by eighths of a power of two."""
    return np.where(counts < 128, counts, np.minimum(128 + np.round(8 * np.log2(np.maximum(counts, 128) / 128)), 255)).astype(np.uint8)


#: The counts that codes stand for.
DECODED = np.concatenate([np.arange(128), 128 * 2 ** (np.arange(128) / 8)]).astype(np.float32)


def bucket_counts(docs: DataFrame, size: int, bits: int = BUCKET_BITS) -> np.ndarray:
    """Occurrences of the shingles of each hash bucket in the whole table of (id, text), coded in a byte each.

    Tasks send their counts in blocks of buckets, and blocks are summed as they arrive: no
    worker holds more than one table of a byte a bucket, however many tasks there are.
    """
    block = min(BLOCK, 1 << bits)

    def sent(counts: np.ndarray, over: list[tuple]) -> Iterator[pa.RecordBatch]:
        rows = counts.reshape(-1, block)
        at, more = (np.concatenate(x) for x in zip((np.zeros(0, np.int64), np.zeros(0, np.int64)), *over))
        order = np.argsort(at // block, kind="stable")
        at, more = at[order], more[order]
        used = np.flatnonzero(rows.any(axis=1))
        low, high = np.searchsorted(at // block, used), np.searchsorted(at // block, used, "right")
        for first in range(0, len(used), 64):
            own, packed = used[first : first + 64], []
            for b, i, j in zip(own, low[first : first + 64], high[first : first + 64]):
                row = rows[b]
                if j > i:
                    row = row.astype(np.uint32)
                    np.add.at(row, at[i:j] % block, more[i:j].astype(np.uint32))
                packed.append(zlib.compress(row.tobytes(), 1))
            yield pa.RecordBatch.from_arrays([pa.array(own.astype(np.int32)), pa.array(packed, pa.binary())], names=["block", "n"])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, over, open_, n, seen = np.zeros(1 << bits, np.uint8), [], [], 0, 0

        def close() -> None:
            found, times = np.unique(np.concatenate([np.zeros(0, np.int32), *open_]), return_counts=True)
            times = times + counts[found]
            counts[found] = np.minimum(times, 255)
            many = times > 255  # what a byte cannot hold is kept beside
            over.append((found[many].astype(np.int64), times[many] - 255))

        for batch in slices(batches, limit=WORK_BYTES):
            open_.append((shingles(batch.column(0), size)[0] >> np.uint64(64 - bits)).astype(np.int32))
            n += len(open_[-1])
            if n > 1 << 20:
                close()
                open_, n, seen = [], 0, seen + n
                if seen >= 1 << 28:  # before a count could pass 32 bits, or too much is kept beside
                    yield from sent(counts, over)
                    counts[:], over, seen = 0, [], 0
        close()
        yield from sent(counts, over)

    def total(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for at, packed in zip(batch.column(0).to_pylist(), batch.column(1)):
                own = zlib.decompress(packed.as_py())
                own = np.frombuffer(own, np.uint8 if len(own) == block else np.uint32)
                sums[at] = sums[at] + own if at in sums else own.astype(np.float32)
        for at, own in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([at], pa.int32()), pa.array([_coded(own).tobytes()], pa.binary())], names=["block", "n"])

    schema = "block int, n binary"
    rows = docs.select("text").mapInArrow(count, schema).repartition("block").mapInArrow(total, schema).toArrow()
    out = np.zeros(1 << bits, np.uint8).reshape(-1, block)
    for at, counts in zip(rows.column("block").to_pylist(), rows.column("n")):
        out[at] = np.frombuffer(counts.as_py(), np.uint8)
    return out.reshape(-1)


def prefixes(docs: DataFrame, size: int, num: int, den: int, counts: np.ndarray) -> DataFrame:
    """(id, sig, n, l, map, tokens): digest and size of the set, its level and parity map, and its prefix in order."""
    bits = counts.size.bit_length() - 1
    shared = docs.sparkSession.sparkContext.broadcast(counts)

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        often, longs = shared.value, pa.list_(pa.int64())
        for batch in slices(batches, limit=WORK_BYTES):
            rows: list[list] = [[], [], [], [], []]
            for own in shingle_sets(batch.column(1), size):
                n, least = len(own), overlap(len(own), num, den)
                top = min(LEVELS, least)
                met = DECODED[often[(own >> np.uint64(64 - bits)).astype(np.int64)]]
                order = np.argsort(met, kind="stable")[: n - least + top]  # own is sorted, so ties are in order of the hash
                cost = np.cumsum(met[order] - 1, dtype=np.float64)[n - least :] * (1 + VERIFY_COST / np.arange(1, top + 1)) if n else np.zeros(1)
                level = int(np.argmin(cost)) + 1
                parity = np.bincount((own >> np.uint64(20) & np.uint64(MAP_BITS - 1)).astype(np.int64), minlength=MAP_BITS) & 1
                for column, value in zip(rows, (digest(own), n, level, np.packbits(parity.astype(np.uint8)).view(np.int64), own[order[: n - least + level]].view(np.int64))):
                    column.append(value)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows[0], pa.binary()), pa.array(rows[1], pa.int32()), pa.array(rows[2], pa.int32()), pa.array(rows[3], longs), pa.array(rows[4], longs)], names=["id", "sig", "n", "l", "map", "tokens"])

    return docs.mapInArrow(go, f"id {docs.schema['id'].dataType.simpleString()}, sig binary, n int, l int, map array<long>, tokens array<long>")


def node(sig: str | Column = "sig") -> Column:
    """A set's number in the search for candidates: 60 bits of its digest."""
    return F.conv(F.substring(F.hex(sig), 1, 15), 16, 10).cast("long")


def whole_sets(docs: DataFrame, size: int) -> DataFrame:
    """(sig, members) of (id, text); equal rows that a task sees again are left out."""

    def go(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[bytes] = set()
        for batch in slices(batches, limit=WORK_BYTES):
            found = {sig: s for s in shingle_sets(batch.column(0), size) if (sig := digest(s)) not in seen}
            seen.update(found)
            yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.binary()), pa.array([s.view(np.int64) for s in found.values()], pa.list_(pa.int64()))], names=["sig", "members"])

    return docs.select("text").mapInArrow(go, "sig binary, members array<long>")


def _maybe(docs: DataFrame, wanted: DataFrame, bits: int = WANTED_BITS) -> DataFrame:
    """Rows of ``docs`` whose id may be in ``wanted``, by a map of fixed size, so that few other texts move."""
    place = F.xxhash64("id").bitwiseAND((1 << bits) - 1)
    at = (place + 1).alias("at")
    maps = wanted.select(at).groupBy(F.expr("bitmap_bucket_number(at)").alias("part")).agg(F.expr("bitmap_construct_agg(bitmap_bit_position(at))").alias("map")).toArrow()
    whole = np.zeros(1 << bits - 3, np.uint8)
    for part, own in zip(maps.column("part").to_pylist(), maps.column("map").to_pylist()):
        own = np.frombuffer(own, np.uint8)
        whole[(part - 1) * len(own) : part * len(own)] = own
    shared = docs.sparkSession.sparkContext.broadcast(whole)

    @F.pandas_udf("boolean")
    def among(places: pd.Series) -> pd.Series:
        at = places.to_numpy()
        return pd.Series(shared.value[at >> 3] >> (at & 7).astype(np.uint8) & 1 == 1)

    return docs.where(among(place))


def _near(x: str, y: str, num: int, den: int) -> Column:
    """False only for pairs whose sizes or parity maps prove that they are below the threshold."""
    n, m = F.col(f"{x}.n"), F.col(f"{y}.n")
    bits = sum((F.bit_count(F.col(f"{x}.map")[k].bitwiseXOR(F.col(f"{y}.map")[k])) for k in range(MAP_BITS // 64)), F.lit(0))
    return (F.least(n, m) * den >= F.greatest(n, m) * num) & (bits * (den + num) <= (n + m) * (den - num))


def _enough(x: str, y: str) -> Column:
    """Whether two sets share k of the tokens of their k-th prefixes, for every k up to the smaller level."""
    upto = lambda side, k: F.slice(F.col(f"{side}.tokens"), F.lit(1), F.col(f"{side}.upto")[k])
    level = F.least(f"{x}.l", f"{y}.l")
    return reduce(Column.__and__, [(level <= k) | (F.size(F.array_intersect(upto(x, k), upto(y, k))) > k) for k in range(LEVELS)])


def _verified(pairs: DataFrame, shared: DataFrame, docs: DataFrame, ids: DataFrame, size: int, num: int, den: int, scratch: Scratch) -> DataFrame:
    """The (a, b), stored, whose maps and prefixes, then whole sets, reach the threshold; only sets of such pairs are built."""
    side = lambda t, x, *cols: t.select(F.col("node").alias(x), F.struct(*cols).alias(f"of_{x}"))
    for x in "ab":
        pairs = pairs.join(side(shared, x, "n", "l", "map", "tokens", "upto"), x)
    pairs = scratch.keep(pairs.where(_near("of_a", "of_b", num, den) & _enough("of_a", "of_b")).select("a", "b").distinct(), "plausible")
    wanted = scratch.keep(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct().join(ids, "node").select(F.col("rep").alias("id")).distinct(), "wanted")
    rows = _maybe(docs, wanted).join(wanted.hint("shuffle_hash"), "id", "left_semi")
    sets = scratch.keep(whole_sets(rows, size).select(node().alias("node"), "members"), "members")
    scratch.drop(wanted)
    both = pairs
    for x in "ab":
        both = both.join(side(sets, x, "members"), x)
    inside = F.size(F.array_intersect("of_a.members", "of_b.members"))
    union = F.size("of_a.members") + F.size("of_b.members") - inside
    found = scratch.keep(both.where(inside * den >= union * num).select("a", "b").distinct(), "found")
    scratch.drop(pairs, sets)
    return found


def links(docs: DataFrame, size: int, num: int, den: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(id, sig, n of every row of (id, text); sig, node and smallest id of every set; links between nodes that connect all that is linked)."""
    scratch = Scratch(docs.sparkSession)
    base = scratch.keep(prefixes(docs, size, num, den, bucket_counts(docs, size)), "prefixes")
    firsts = base.where("n > 0 and id is not null").groupBy("sig").agg(F.min("id").alias("rep"), F.first(F.struct("n", "l", "map", "tokens")).alias("of"))
    sigs = scratch.keep(firsts.select("sig", node().alias("node"), "rep", "of.*"), "sets")
    classes = scratch.keep(base.select("id", "sig", "n"), "classes")
    del firsts
    scratch.drop(base)

    # What sets share: a row of each (shingle, set), then a row of each set. Any of the first LEVELS common shingles counts here.
    postings = sigs.select("node", "n", F.posexplode("tokens").alias("at", "token"))
    size_reach = F.shiftleft(F.col("n").cast("long"), 32) + reach(F.col("n"), F.greatest(F.col("at") - (LEVELS - 1), F.lit(0)), num, den)
    two = postings.withColumn("of", size_reach).groupBy("token").agg(F.count("*").alias("df"), F.min("of").alias("x"), F.max("of").alias("y"))
    size_of, reach_of = (lambda x: F.shiftright(x, 32)), (lambda x: F.col(x).bitwiseAND((1 << 32) - 1))
    meet = (size_of("y") <= reach_of("x")) & (size_of("x") <= reach_of("y"))
    often = scratch.keep(two.where((F.col("df") > 2) | (F.col("df") == 2) & meet).select("token", "df"), "often")  # apart from the join, so that a token of very many sets can be split there
    own = F.sort_array(F.collect_list(F.struct("at", "token", "df")))
    places = postings.select("node", "at", "token").join(often.hint("merge"), "token").groupBy("node").agg(own.alias("own"))
    base_size = F.col("n") - overlap(F.col("n"), num, den)
    within = lambda k: F.size(F.filter("own", lambda x: x["at"] < base_size + k))
    shared = sigs.select("node", "n", "l", "map").join(places.hint("merge"), "node").withColumn("upto", F.array(*map(within, range(1, LEVELS + 1))))
    shared, met = scratch.observed(shared.where("upto[0] > 0").select("node", "n", "l", "map", "own", F.col("own.token").alias("tokens"), "upto"), "shared", rows=F.sum(F.col("upto")[0]))
    enough = FEW_PAIRS * (met["rows"] or 0)
    ids = scratch.keep(sigs.select("sig", "node", "rep"), "nodes")
    del postings, places, two
    scratch.drop(often, sigs)
    verified = lambda pairs: _verified(pairs, shared, docs, ids, size, num, den, scratch)
    nodes = shared.select("node", "n", F.explode(F.slice("own", F.lit(1), F.col("upto")[0])).alias("own")).select("node", "n", "own.token", "own.df", reach(F.col("n"), F.col("own.at"), num, den).alias("reach"))
    meet = (F.col("x.n") <= F.col("y.reach")) & (F.col("y.n") <= F.col("x.reach"))

    few = nodes.where(F.col("df") <= FEW_SETS).drop("df")
    pairs = few.alias("x").join(few.alias("y").hint("merge"), (F.col("x.token") == F.col("y.token")) & (F.col("x.node") < F.col("y.node")) & meet)
    edges = verified(pairs.select(F.col("x.node").alias("a"), F.col("y.node").alias("b")).distinct())
    labels, open_, before = components(edges, scratch), scratch.keep(nodes.where(F.col("df") > FEW_SETS).drop("df"), "open"), 0
    for step in range(TIE_ROUNDS + 1):
        tied = open_.join(labels.hint("merge"), open_.node == labels.id, "left").withColumn("component", F.coalesce("component", "node")).drop("id")
        chance = F.xxhash64("node", F.lit(step))
        groups = tied.groupBy("token", "component").agg(F.count("*").alias("k"), F.min_by("node", chance).alias("one"))
        best = F.struct("k", F.xxhash64("component", F.lit(step)), "component", "one")
        main = groups.groupBy("token").agg(F.max(best).alias("main"), F.count("*").alias("groups"), F.sum("k").alias("rows")).where("groups > 1")
        tied = tied.join(main.select("token", F.col("main.component").alias("main"), F.col("main.one").alias("hub"), "rows").hint("merge"), "token")
        tied, state = scratch.observed(tied, "tied", pairs=F.sum(F.when(F.col("component") != F.col("main"), F.col("rows"))))
        scratch.drop(open_)
        if step == TIE_ROUNDS or (state["pairs"] or 0) <= enough or before and 2 * state["pairs"] > before:
            break
        before = state["pairs"]
        minor = tied.where("component <> main")
        second = minor.groupBy("token").agg(F.min_by("node", chance).alias("other"))
        pairs = minor.select("node", F.col("hub").alias("other")).unionByName(minor.join(second.hint("merge"), "token").select("node", "other")).where("node <> other")
        pairs = pairs.select(F.least("node", "other").alias("a"), F.greatest("node", "other").alias("b")).distinct()
        found = verified(pairs)
        open_ = scratch.keep(tied.select(open_.columns), "open")
        more = scratch.keep(edges.unionByName(found).distinct(), "found")
        scratch.drop(tied, edges, found, labels)
        edges, labels = more, components(more, scratch)
    heads = shared.select("node", "map", F.slice("tokens", F.lit(1), F.least(F.lit(HEAD), F.col("upto")[0])).alias("head"))
    headed = tied.join(heads.hint("merge"), "node")
    x, y = headed.where("component <> main").alias("x"), headed.alias("y")
    one_way = (F.col("y.component") == F.col("y.main")) | (F.col("x.node") < F.col("y.node"))
    common = F.array_intersect("x.head", "y.head")
    once = (F.size(common) == 0) | (common[0] == F.col("x.token"))
    met = x.join(y, (F.col("x.token") == F.col("y.token")) & (F.col("x.component") != F.col("y.component")) & one_way & meet & _near("x", "y", num, den) & once)
    met = scratch.keep(met.select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b")).distinct(), "met")
    last = verified(met)
    out = scratch.keep(edges.unionByName(last), "found")
    scratch.drop(shared, met, tied, labels, edges, last)
    return classes, ids, out


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 5, threshold: tuple[int, int] = (80, 100)) -> DataFrame:
    """(id, n_shingles, component_id): the component is the smallest id that links reach."""
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    classes, ids, edges = links(source, size, *threshold)
    labels = components(edges).withColumnRenamed("id", "node")
    known = ids.join(labels, "node", "left").withColumn("component", F.coalesce("component", "node"))
    least = known.groupBy("component").agg(F.min("rep").alias("component_id"))
    known = Scratch(docs.sparkSession).keep(known.join(least, "component").select("sig", "component_id"), "classes")
    linked = (F.col("n") > 0) & F.col("id").isNotNull()
    return classes.join(known, "sig", "left").select(F.col("id").alias(id_col), F.col("n").cast("long").alias("n_shingles"), F.when(linked, F.col("component_id")).otherwise(F.col("id")).alias("component_id"))


def op6_jaccard(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"), size=4, threshold=(85, 100))
