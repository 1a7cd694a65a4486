"""Operators against brute force on small tables, with nulls, empties, repeats and clashing columns."""

import hashlib
import itertools
import random
import tracemalloc
import zlib
from functools import cache

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from chronopath.llm import components, decontaminate, jaccard, lengths, linechunks, packing, quality, substrings, tiff, toxicity, warc
from chronopath.llm.common import BpeBytes, Scratch, WordColumn, bpe, tokenizer_path

rng = random.Random(4)
WORDS = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 7))) for _ in range(400)]


def text(n, lines=False):
    return "".join(w + ("\n" if lines and rng.random() < 0.15 else " ") for w in rng.choices(WORDS, k=n)).strip()


@cache
def corpus():
    base = [text(120, True) for _ in range(12)]
    passage = text(60)
    out = base + [base[0], base[0], base[1].upper()]
    out += [base[2] + " " + text(4), base[3][: len(base[3]) * 9 // 10], passage + " " + text(30), text(25) + " " + passage + " " + text(25), text(20) + "\n" + passage]
    out += ["", None, "one two", "one  two", "one two three", " \n\t ", "x " * 300, "x " * 320, text(900, True), "Ünïcödé wörds here " * 20]
    return [(i * 3 + 1, t) for i, t in enumerate(out)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, "extra", 5) for i, t in corpus()], "doc_id long, text string, sequence_id string, rank int").cache()


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("false")


def words(t):
    return (t or "").encode().split()


def test_bpe_equals_the_tokenizers_library():
    from tokenizers import Tokenizer

    other = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    odd = [" ", " ", "\xa0", "\u3000", "\t", "\r", "\n", "\x1c", "\x85", "\u2003", "a", "fußball-ÿz", "Слово,", "12x", "'s", "é", "1", "!", "漢", "'", "\U0001f600", "<|endoftext|>"]
    mixed = ["".join(rng.choices(odd[: len(odd) - (i % 9 > 0)], k=rng.randint(0, 12))) for i in range(20_000)]
    for t in mixed + [t for _, t in corpus() if t] + ["a  b", " a", "a ", "  ", "it's\n\nthat \t x", "<|endoftext|> 12 345", "a  b", " x \r\n y"]:
        assert np.frombuffer(bpe().encode(t), "<u4").tolist() == other.encode(t, add_special_tokens=False).ids


def test_bpe_asks_the_library_once_for_a_word():
    from tokenizers import Tokenizer

    class Asked:
        def __init__(self, model):
            self.model, self.words = model, []

        def tokenize(self, word):
            self.words.append(word)
            return self.model.tokenize(word)

    other, encoder = Tokenizer.from_file(tokenizer_path()), BpeBytes()
    encoder.model = Asked(encoder.model)
    for t in ("a word, a word. (word) word!\nword 12 12,", "word; word 12."):  # signs beside a word make no other word of it
        assert np.frombuffer(encoder.encode(t), "<u4").tolist() == other.encode(t, add_special_tokens=False).ids
    assert len(encoder.model.words) == len(set(encoder.model.words))
    texts = [None, "", "don't word", "<|endoftext|> word", " ", "\n", "word", None, "a <|endoftext|>", "× ×1 ÷é"]
    for part in (slice(0, None), slice(3, 6), slice(0, 2), slice(0, 0)):
        ids, starts = encoder.column(pa.array(texts, pa.string())[part])
        assert [ids[a:b].tolist() for a, b in itertools.pairwise(starts)] == [other.encode(t or "", add_special_tokens=False).ids for t in texts[part]]


def test_packing(docs, empty):
    rows = packing.pack(docs, capacity=256).collect()
    by_doc, by_bin = {}, {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_bin.setdefault(r.sequence_id, []).append(r)
    for i, t in corpus():
        ids, own = bpe().encode(t) + b"\0" * 4, sorted(by_doc[i], key=lambda r: r.piece)
        assert [r.start for r in own] == [s for s, _ in packing.cut(len(ids) // 4, 256)] and all(r.length == 256 for r in own[1:])
        assert all(r.ids_crc32 == zlib.crc32(ids[4 * r.start : 4 * (r.start + r.length)]) for r in own)
    for own in by_bin.values():
        at = 0
        for r in sorted(own, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 256
    assert len(by_bin) <= 1 + -(-sum(r.length for r in rows) // 256) and packing.pack(empty).count() == 0


def test_fullest_combination_is_the_best():
    gen = random.Random(1)
    for _ in range(60):
        lengths_, room = {gen.randint(1, 30): gen.randint(1, 4) for _ in range(6)}, gen.randint(1, 80)
        sums = {0}
        for k, n in lengths_.items():
            sums = {s + k * j for s in sums for j in range(n + 1)}
        found = packing.fullest(sorted(lengths_.items(), reverse=True), room)
        assert sum(k * n for k, n in found.items()) == max(s for s in sums if s <= room) and all(n <= lengths_[k] for k, n in found.items())


def test_lengths(docs, empty):
    truth = [len(bpe().encode(t)) // 4 for _, t in corpus()]
    hist = lengths.histogram(docs).cache()
    for r in hist.collect():
        assert (r.n_docs, r.docs_reaching) == (truth.count(r.length), sum(x >= r.length for x in truth))
        assert r.tokens_reaching == sum(x for x in truth if x >= r.length) and r.truncated_tokens == sum(min(x, r.length) for x in truth)
    at = lengths.at_limit(hist, 100).first()
    assert (at.docs_cut, at.tokens_kept) == (sum(x > 100 for x in truth), sum(min(x, 100) for x in truth))
    assert lengths.quantile(hist, 0.5).first()[0] == sorted(truth)[(len(truth) - 1) // 2]
    assert lengths.histogram(empty).count() == 0


@pytest.mark.parametrize("compression", [tiff.NONE, tiff.LZW, tiff.DEFLATE, tiff.PACKBITS])
@pytest.mark.parametrize("dtype,predictor", [("u1", 2), ("u2", 1), ("i2", 2), ("f4", 3), ("f8", 3)])
def test_tiff_round_trip(compression, dtype, predictor):
    gen = np.random.default_rng(3)
    page = (gen.integers(0, 9, (37, 50, 3)) * 7).astype(dtype)
    for tile in (None, (16, 32)):
        got = [x for _, x in tiff.decode(tiff.encode([page, page[:5, :, :1]], compression, predictor, 10, tile))]
        assert (got[0] == page).all() and (got[1] == page[:5, :, :1]).all()


def test_lzw_and_packbits_long_inputs():
    gen = np.random.default_rng(0)
    for data in (gen.integers(0, 256, 40_000, dtype=np.uint8).tobytes(), b"ab" * 9000, b"", b"a", b"\x00" * 5000):
        assert tiff.lzw_decode(tiff.lzw_encode(data)) == data and tiff.unpack_bits(tiff.pack_bits(data)) == data


def test_tiff_pages_and_damage(spark):
    good = tiff.encode([np.arange(12, dtype=np.uint8).reshape(3, 4, 1)] * 2)
    looped = bytearray(good)
    rows = spark.createDataFrame([(1, good), (2, None), (3, b"nope"), (4, good[:-30])], "id long, media binary")
    got = tiff.pages(rows, "id").collect()
    assert [(r.page, r.width, r.height, r.error) for r in got if r.id == 1] == [(0, 4, 3, None), (1, 4, 3, None)]
    assert all(any(r.error for r in got if r.id == i) for i in (2, 3, 4)) and len(looped) == len(good)


def test_tiff_digests(docs, empty):
    got = {r.doc_id: r for r in tiff.digests(tiff.text_media(docs)).collect()}
    for i, t in corpus():
        payload = (t or "").encode()
        padded = payload + b"\xff" * (-len(payload) % 576 if payload else 576)
        assert (got[i].n_bytes, got[i].payload_bytes, got[i].payload_sha256, got[i].tail_crc32) == (len(payload), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-32:]))
    assert tiff.digests(tiff.text_media(empty)).count() == 0


def test_warc(spark, tmp_path):
    long, other = "a" * 1500, "é" * 700
    rows = [(1, "http://a/1", long), (2, None, long), (3, "http://a/3\r\nX: y", long), (4, "u", None), (5, "u", "b" * 10), (6, "u", "b" * 10), (7, "u", other), (7, "u", other), (None, "u", long)]
    pages = spark.createDataFrame([(*r, 1) for r in rows], "page_id long, url string, html string, digest int")
    stored = warc.write_pages(pages)
    got = warc.read_bundles(stored).collect()
    assert len(got) == len(rows)
    for r in got:
        body = {1: long, 2: long, 3: long, 4: "", 5: "b" * 10, 6: "b" * 10, 7: other, None: long}[r.page_id].encode()
        assert (r.payload_bytes, r.payload_digest) == (len(body), hashlib.sha1(body).hexdigest())
        assert (r.record_type, r.refers_to) == (("revisit", 3) if r.page_id in (1, 2) else ("response", None))
    assert warc.write_pages(pages.where("false")).count() == 0
    bundle = stored.first().data
    reader = warc.Reader(bytes(bundle))
    key = reader.index[0][0]
    assert reader.read(key)[0]["WARC-Record-ID"] == f"<{warc.URN}{key}>"
    import zstandard

    assert zstandard.ZstdDecompressor().stream_reader(bytes(bundle), read_across_frames=True).read()[:8] == b"WARC/1.1"
    assert warc.export_bundles(stored, str(tmp_path)).count() == stored.count() == len(list(tmp_path.glob("*.zst")))


def test_warc_keeps_payloads_of_repeated_ids(spark):
    a, b = "a" * 1500, "b" * 1500
    found = warc.read_bundles(warc.write_pages(spark.createDataFrame([(1, a), (2, a), (1, b)], "page_id long, html string"))).collect()
    assert sorted((r.page_id, r.record_type, r.refers_to or 0, (r.payload or b"").decode()[:1]) for r in found) == [(1, "response", 0, "b"), (1, "revisit", 2, ""), (2, "response", 0, "a")]


def test_frames_are_independent():
    bundle = warc.Bundle(frame_bytes=2000)
    for i in range(50):
        bundle.add(str(i), warc.record(i, "u", b"x" * 300, "d", None, "2000-01-01T00:00:00Z"))
    reader = warc.Reader(bundle.close())
    assert len(reader.frames) > 5 and [int(f["WARC-Record-ID"].strip("<>").removeprefix(warc.URN)) for f, _, _ in reader.records()] == list(range(50))


def shingles(t, n):
    w = (t or "").encode().lower().split()
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set())


def groups(rows, n, num, den):
    sets = {i: shingles(t, n) for i, t in rows}
    root = {i: i for i in sets}

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            both = len(sets[a] & sets[b])
            if a < b and both and den * both >= num * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


@pytest.mark.parametrize("n,num", [(4, 85), (5, 80)])
def test_near_duplicates(docs, empty, n, num):
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.near_duplicates(docs, size=n, threshold=(num, 100)).collect()}
    assert got == groups(corpus(), n, num, 100)


def test_word_hashes_are_those_of_the_words():
    texts = [t for _, t in corpus()] + ["x" * 300 + " Y" * 3, "A\x0bb\x1cC d", "\n", "é É"] + ["ab " * 200_000]
    for lower in (False, True):
        found, seen = WordColumn(pa.array([None, *texts]), lower), {}
        own = [(t or "").encode() for t in texts]
        own = [(t.lower() if lower else t).split() for t in own]
        assert found.sizes.tolist() == [0, *map(len, own)]
        for word, h in zip((w for t in own for w in t), found.hashes.tolist()):
            assert seen.setdefault(word, h) == h
        assert len(set(seen.values())) == len(seen)


def test_near_duplicates_of_repeated_ids(spark):
    a, b = text(60), text(60)
    rows = [(1, a), (1, b), (1, a), (2, "other words"), (3, b + " more"), (None, b)]
    found = jaccard.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), size=4, threshold=(85, 100)).collect()
    assert sorted((r.doc_id or 0, r.n_shingles, r.component_id or 0) for r in found) == [(0, 57, 0), (1, 57, 1), (1, 57, 1), (1, 57, 1), (2, 1, 2), (3, 58, 1)]


def test_near_duplicates_empty(empty):
    assert jaccard.near_duplicates(empty).count() == 0


def test_near_duplicates_in_a_large_group(spark):
    base = [rng.choice(WORDS) for _ in range(60)]
    rows = []
    for i in range(150):
        own = list(base)
        for _ in range(rng.randint(0, 4)):
            own[rng.randrange(60)] = rng.choice(WORDS)
        rows.append((i, " ".join(own)))
    rows += [(1000 + i, " ".join(base[:20]) + " " + text(25)) for i in range(40)]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), size=4, threshold=(85, 100)).collect()}
    assert got == groups(rows, 4, 85, 100)


def test_near_duplicates_at_any_place_of_the_order(spark, monkeypatch):
    """Sizes about the threshold, all shingles in order of their hashes alone, groups of shingles compared at once or in rounds."""
    monkeypatch.setattr(jaccard, "bucket_counts", lambda *_: np.ones(1 << 16, np.uint8))
    rows = []
    for size in (5, 8, 20, 45, 90):
        base = [rng.choice(WORDS) for _ in range(size)]
        for k in range(24):
            own = base[: size - rng.randint(0, max(1, size // 7))] + rng.choices(WORDS, k=rng.randint(0, max(1, size // 9)))
            if k % 3 == 0:
                own[rng.randrange(len(own))] = rng.choice(WORDS)
            rows.append((len(rows), " ".join(own)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    monkeypatch.setattr(jaccard, "FEW_SETS", 3, raising=False)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.near_duplicates(docs, size=4, threshold=(85, 100)).collect()}
    assert got == groups(rows, 4, 85, 100)


def test_sets_that_cannot_meet_are_not_tied(spark, monkeypatch):
    """Texts and their first halves share shingles, but no order of them lets such sizes reach the threshold: none goes into the rounds."""
    rows, made = [], []
    for i in range(30):
        long = [f"w{i}_{k}" for k in range(100)]
        rows += [(2 * i, " ".join(long)), (2 * i + 1, " ".join(long[:50]))]
    monkeypatch.setattr(jaccard, "bucket_counts", lambda *_: np.ones(1 << 16, np.uint8))
    plain = Scratch.keep

    def keep(self, df, name="t"):
        out = plain(self, df, name)
        made.extend([out.count()] * (name in ("tied", "shared")))
        return out

    monkeypatch.setattr(Scratch, "keep", keep)
    got = jaccard.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), size=4, threshold=(85, 100)).collect()
    assert all(r.component_id == r.doc_id for r in got) and len(made) >= 2 and sum(made) == 0


def test_components(spark):
    chain = [(i, i + 1) for i in range(40)] + [(100, 90), (95, 100), (7, 7)]
    got = {r.id: r.component for r in components.components(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 90: 90, 95: 90, 100: 90}


def test_substrings(docs, empty):
    window, first, truth = 50, {}, {}
    for i, t in corpus():
        for k in range(len(words(t)) - window + 1):
            first.setdefault(tuple(words(t)[k : k + window]), i)
    for i, t in corpus():
        w, gone = words(t), set()
        for k in range(len(w) - window + 1):
            if first[tuple(w[k : k + window])] < i:
                gone |= set(range(k, k + window))
        truth[i] = (len(w), len(gone), hashlib.sha256(b" ".join(x for k, x in enumerate(w) if k not in gone)).hexdigest())
    assert {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substrings.digest(docs).collect()} == truth
    assert sum(n > 0 for _, n, _ in truth.values()) >= 5 and substrings.digest(empty).count() == 0


def test_intervals_are_maximal():
    assert substrings.intervals(np.array([1, 2, 3, 60, 10, 53]), 50).tolist() == [[1, 110]]
    assert substrings.intervals(np.array([1, 52]), 50).tolist() == [[1, 51], [52, 102]] and substrings.intervals(np.array([], int), 50).tolist() == []


def test_line_chunks(spark, docs, empty):
    block = "\n".join(text(6) for _ in range(8))
    rows = [(1, block + "\n" + text(5)), (2, text(5) + "\n" + block), (3, None), (4, ""), (5, text(5) + "\nnew\n" + block + "\ntail"), (5, "other"), (None, block), (7, "a"), (8, "\n\n\n\n"), (9, "\n\n\n\n")]
    table = spark.createDataFrame([(i, t, 9, "k") for i, t in rows], "doc_id long, text string, lines_removed int, key string")
    got = {(r.doc_id, r.text): r.lines_removed for r in linechunks.remove(table).collect()}
    assert got[1, rows[0][1]] == 0 and got[None, block] == 0 and got[3, None] == 0 and got[8, "\n\n\n\n"] == 0 and got[5, "other"] == 0
    assert sum(n for (i, _), n in got.items() if i in (2, 5)) >= 4
    assert linechunks.remove(empty).count() == 0


def test_decontamination(spark, docs, empty):
    items = [(i, text(rng.randint(15, 59)) + ". " + text(6)) for i in range(8)] + [(8, text(150)), (9, "short"), (10, None)]
    bench = spark.createDataFrame(items, "item_id long, text string")
    rows = [(100 + i, text(rng.randint(0, 200)) + " " + t.upper() + "xy " + text(50)) for i, t in items[:9]] + [(200 + i, text(300)) for i in range(5)] + [(300, None), (301, ""), (302, items[0][1][:30])]
    found = decontaminate.contaminated(spark.createDataFrame(rows, "doc_id long, text string"), bench).collect()
    assert {(r.doc_id, r.item_id) for r in found} == {(100 + i, i) for i in range(9)}
    assert decontaminate.contaminated(empty, bench).count() == 0 and decontaminate.contaminated(docs, bench.where("false")).count() == 0


def test_decontamination_of_short_items(spark):
    items = spark.createDataFrame([(1, "five rather short test words"), (2, "three words only")], "item_id long, text string")
    docs = spark.createDataFrame([(1, text(50) + " five rather short test words " + text(50)), (2, "five rather short words test " + text(40)), (3, "three words only " + text(30))], "doc_id long, text string")
    assert [(r.doc_id, r.item_id if "item_id" in r else r.item) for r in decontaminate.contaminated(docs, items).collect()] == [(1, 1)]


def test_decontamination_does_not_depend_on_blocks(spark, docs, monkeypatch):
    items = spark.createDataFrame([(i, t) for i, t in corpus() if t and 20 < len(t.split()) < 200], "item_id long, text string")
    whole = sorted(map(str, decontaminate.contaminated(docs, items).collect()))
    monkeypatch.setattr(decontaminate, "BLOCK_CHARS", 2000)
    assert whole and sorted(map(str, decontaminate.contaminated(docs, items).collect())) == whole


def test_decontamination_verifies_every_passage(spark):
    """The best passage quotes a part of the item only; the item stands far from it, with a few words changed."""
    gen = random.Random(3)
    own = ["".join(gen.choices("klmnopqrst", k=8)) for _ in range(160)]
    far = lambda: " ".join("".join(gen.choices("abcdef", k=6)) for _ in range(900))
    edited = [w if i % 40 != 20 else "changed" for i, w in enumerate(own)]
    bench = spark.createDataFrame([(1, " ".join(own))], "item_id long, text string")
    rows = [(1, f"{far()} {' '.join(own[:80])} {far()} {' '.join(edited)} {far()}"), (2, f"{far()} {' '.join(own[:80])} {far()}")]
    found = decontaminate.contaminated(spark.createDataFrame(rows, "doc_id long, text string"), bench).collect()
    assert [(r.doc_id, r.item_id) for r in found] == [(1, 1)]


def test_block_max_wand_finds_all_above_threshold():
    items = [(i, text(rng.randint(10, 60))) for i in range(400)]
    index = decontaminate.Index(items, {w.encode(): k for k, w in enumerate(WORDS)}, 1000, threshold=0.25)
    for _ in range(40):
        query = {index.vocabulary[w.encode()] for w in rng.choices(WORDS, k=40) if w.encode() in index.vocabulary}
        truth = {}
        for t in query:
            for k, s in zip(*index.lists[t]):
                truth[k] = truth.get(k, 0) + s
        assert {k: round(s, 9) for k, s in index.retrieve(query)} == {k: round(s, 9) for k, s in truth.items() if s >= 0.25}


@pytest.fixture(scope="module")
def labelled(spark):
    rows = []
    for i in range(400):
        bad = i % 5 == 0
        own = text(rng.randint(20, 80)).split()
        for _ in range(3 if bad else 0):
            own[rng.randrange(len(own))] = rng.choice(["zorx", "zorxa", "zorxich", "quuz"])
        junk = i % 3 == 0
        rows.append((i, " ".join(w.upper() + "!!" for w in own) if junk else " ".join(own), int(not junk), int(bad)))
    rows += [(1000, None, None, 1), (1001, "", 1, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, quality int, toxic int").cache()


def test_toxicity(labelled, docs):
    model = toxicity.fit_tables(labelled.select("doc_id", "text"), labelled.select("doc_id", "toxic"))
    held = toxicity.score(labelled, model).where("toxic is not null and text is not null").where(toxicity.fold("doc_id", 4) == 2).collect()
    assert sum((r.score >= 0.5) == r.toxic for r in held) >= 0.9 * len(held)
    assert all(0 <= r.score <= 1 for r in toxicity.score(docs, model).collect())
    none = toxicity.fit_tables(labelled.select("doc_id", "text"), labelled.select("doc_id", "toxic").where("toxic = 0"))
    assert none.constant == 0.0


def test_kneser_ney_probabilities_add_up():
    keys, _ = toxicity.grams([w.encode() for w in WORDS], 3)
    found = np.unique(keys)
    p = toxicity.continuation(found, 3)
    _, at = np.unique(found >> np.uint64(8), return_inverse=True)
    assert (np.bincount(at, p) <= 1 + 1e-5).all() and (p > 0).all()


def test_kneser_ney_ratios_equal_a_plain_recursion():
    """Log ratios of n-grams against a dictionary-based model, order 4."""
    order, d = 4, toxicity.DISCOUNT
    tokens = [w.encode() for w in WORDS[:60]]
    keys, word = toxicity.grams(tokens, order)
    weight = np.array([[rng.randint(0, 3), rng.randint(0, 3)] for _ in tokens])
    seen, at = np.unique(keys, return_inverse=True)
    counts = [np.bincount(at, weight[word, c]).astype(np.int64) for c in (0, 1)]
    some = counts[0] + counts[1] > 0
    seen, counts = seen[some], [c[some] for c in counts]
    text_of = lambda key, n: bytes(int(key) >> 8 * k & 255 for k in range(n - 1, -1, -1))
    left = {n: {} for n in range(1, order)}  # n-gram -> different bytes before it
    for g in (text_of(k, order) for k in seen):
        for n in range(order - 1, 0, -1):
            left[n].setdefault(g[-n:], set()).add(g[-n - 1])

    def shared(g):
        if len(g) == 1:
            n = sum(len(x) for x in left[1].values())
            return 0.999 * len(left[1].get(g, ())) / n + 0.001 / 256
        same = {x: len(v) for x, v in left[len(g)].items() if x[:-1] == g[:-1]}
        return (max(same.get(g, 0) - d, 0) + d * len(same) * shared(g[1:])) / sum(same.values())

    pairs = np.zeros(1 << 16, np.float32)
    for g in left[2]:
        pairs[g[0] << 8 | g[1]] = shared(g)
    found, back = toxicity.ratios(seen, counts[0], counts[1], pairs, order)
    for k, key in enumerate(seen):
        g, logs, backs = text_of(key, order), [], []
        for c in (0, 1):
            same = [int(n) for n, x in zip(counts[c], seen) if text_of(x, order)[:-1] == g[:-1]]
            total, types = sum(same), sum(n > 0 for n in same)
            off = d * types / total if total else 1.0
            logs.append(np.log(max(int(counts[c][k]) - d, 0) / max(total, 1) + off * shared(g[1:])))
            backs.append(np.log(off))
        assert abs(found[k] - (logs[0] - logs[1])) < 1e-3 and abs(back[k] - (backs[0] - backs[1])) < 1e-4


def test_toxicity_block_memory():
    """Cutting a block into words takes a few times its text, and gives the words that cutting it at once gives."""
    texts = [None, "", " ".join(rng.choices(WORDS, k=1000)).title(), *(" ".join(rng.choices(WORDS, k=1000)) for _ in range(700)), "Ünï \x00 x\x00", "y" * 3000]
    column = pa.array(["left out", *texts]).slice(1)
    size = sum(len((t or "").encode()) for t in texts)

    def words():
        return {k: w.split() for k, w in toxicity.Block(column).asked(5)}

    words()
    tracemalloc.start()
    try:
        found = words()
        assert size > 3 << 20 and tracemalloc.get_traced_memory()[1] < 6 * size
    finally:
        tracemalloc.stop()
    whole, block = WordColumn(column, lower=True), toxicity.Block(column)
    assert sorted(w for own in found.values() for w in own) == sorted({w for t in texts for w in (t or "").encode().lower().split()})
    assert all((WordColumn(pa.array([w.decode() for w in own])).hashes % np.uint64(5) == k).all() for k, own in found.items())
    assert (np.concatenate([block.hashes[block.places(part)] for part in block.parts()]) == whole.hashes).all()
    assert sum(len(part.starts) - 1 for part in block.parts()) == len(texts)
    assert toxicity.block_name(column) == toxicity.block_name(pa.array(texts)) != toxicity.block_name(pa.array(texts[1:] + texts[:1]))


def test_toxicity_counts_every_ngram(spark):
    """More n-grams than a table of 2^22 hashed places holds apart; words never seen back off."""
    gen = random.Random(9)
    made = [bytes(gen.choices(b"abcdefghijklmnopqrstuvwxyz\xc3\xa9", k=9)) for _ in range(4000)]
    seen = [(w, gen.randint(0, 3), gen.randint(1, 4)) for w in dict.fromkeys(made[:3000])]
    keys, word = toxicity.grams([w for w, _, _ in seen])
    found, at = np.unique(keys, return_inverse=True)
    toxic, ordinary = (np.bincount(at, np.array([w[i] for w in seen])[word]) for i in (1, 2))
    counts = toxicity.gram_counts(spark.createDataFrame(seen, "word binary, toxic long, ordinary long")).cache()
    assert {(r.key % 2**64, r.toxic, r.ordinary) for r in counts.collect()} == set(zip(found.tolist(), toxic.tolist(), ordinary.tolist())) and counts.count() == len(found)

    shared = toxicity.continuation(found & toxicity._low(7), 7)  # all at once, not by pairs
    whole = {}
    for key, *pair, p in zip(found.tolist(), toxic.tolist(), ordinary.tolist(), shared.tolist()):
        whole.setdefault(key >> 8, []).append((key, pair, p))
    known = {}
    for context, own in whole.items():
        total, follow = ([f(pair[c] for _, pair, _ in own) for c in (0, 1)] for f in (sum, lambda x: sum(n > 0 for n in x)))
        back = [0.75 * follow[c] / total[c] if total[c] else 1.0 for c in (0, 1)]
        known[context, None] = np.log(back[0] / back[1])
        for key, pair, p in own:
            known[context, key] = np.log((max(pair[0] - 0.75, 0) / max(total[0], 1) + back[0] * p) / (max(pair[1] - 0.75, 0) / max(total[1], 1) + back[1] * p))
    table = toxicity.ratio_table(counts).cache()
    for r in table.collect():
        key = r.key % 2**64
        assert abs(r.seen - known[key >> 8, key]) < 1e-3 and abs(r.unseen - known[key >> 8, None]) < 1e-3
    model = toxicity.Model(table, np.zeros(1), np.ones(1), np.zeros(1 + toxicity.N_EVIDENCE))
    ascii_ = [w.decode() for w in made if w.isascii()]
    rows = toxicity.score(spark.createDataFrame([(w,) for w in ascii_], "text string").repartition(3), model).collect()
    assert sorted(r.text for r in rows) == sorted(ascii_)
    for r in rows:
        own = toxicity.grams([r.text.encode()])[0].tolist()
        assert abs(r.mean_ratio - sum(known.get((k >> 8, k), known.get((k >> 8, None), 0.0)) for k in own)) < 1e-2


def test_quality(labelled, docs):
    model = quality.fit_tables(labelled.select("doc_id", "text"), labelled.select("doc_id", "quality"))
    held = quality.score(labelled, model).where("quality is not null and text is not null and text <> ''").where(quality.fold("doc_id", 5) == 0).collect()
    assert sum((r.score >= 0.5) == r.quality for r in held) >= 0.95 * len(held)
    scored = quality.score(docs, model)
    assert 0 < quality.keep_top(scored, 0.3).count() < docs.count()


def test_pipeline(spark, labelled, tmp_path):
    import corpus_pipeline

    items = [(i, text(40)) for i in range(3)]
    block = "\n".join(text(6) for _ in range(10))
    clean = [(2000 + i, text(80)) for i in range(10)]
    rows = [(r.doc_id, r.text) for r in labelled.collect()] + clean + [(3000, clean[0][1]), (3001, clean[1][1] + " end"), (3002, text(30) + " " + items[0][1] + " " + text(9)), (3003, block), (3004, block + "\n" + text(30)), (3005, text(50) + " zorx zorxa quuz zorxich")]
    spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    labelled.drop("text").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs, kept = spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = Scratch(spark).keep(stage(spark, docs.withColumn("extra", F.lit(1)), str(tmp_path)))
        kept[name] = {r.doc_id for r in docs.collect()}
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars", "extra"]
    assert 3005 not in kept["toxicity"] and {i for i, _ in clean} <= kept["decontamination"]
    assert {3000, 3001, 3002} & kept["near_duplicates"] == {3002} and 3002 not in kept["decontamination"] and 3003 in kept["decontamination"]
    packed = {r.doc_id for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert packed == kept["decontamination"]


def test_counts_that_order_shingles_in_a_byte_each(spark):
    """Coded sums over several tasks equal plain counts to a sixteenth of a power of two, also beyond what a byte and a task hold."""
    texts = ["a b c d e", "a b c d " * 300, None, "", "x", "b c d e f g"] * 4
    docs = spark.createDataFrame(list(enumerate(texts)), "id long, text string").repartition(3)
    found = jaccard.bucket_counts(docs, 4, bits=16)
    assert found.dtype == np.uint8 and len(jaccard.bucket_counts(docs, 4)) >= 1 << 24
    own, _ = jaccard.shingles(pa.array(texts), 4)
    plain = np.bincount((own >> np.uint64(48)).astype(np.int64), minlength=1 << 16)
    assert plain.max() > 1000 and (np.abs(np.log2(np.maximum(jaccard.DECODED[found], 0.5)) - np.log2(np.maximum(plain, 0.5))) <= 1 / 16 + 1e-6).all()
