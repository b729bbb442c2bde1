"""The ten operators on small tables against brute force, round trips and held-out labels; nulls, ties, empty tables."""
import collections
import hashlib
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from signgraph.llm import bytescan, lines, media, packing, pieces, quality, rules, simhash, suffix, toxicity, warc

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, left string"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and long texts, repeated rows, an extra column."""
    words = " ".join(f"w{i % 37}x{i % 11}" for i in range(400))
    rows = [(1, None, None, None, "a"), (2, "", "en", "s", "b"), (3, words, "en", "s", None), (4, words, "en", "s", "c"), (4, words, "en", "s", "c"), (5, words[:900] + " tail\none two three four five\nsix", "de", None, "d"), (6, "one two three four five", "en", "s", "e"), (7, "\n\n \t", "en", "s", "f"), (8, "x" * 5000, "en", "s", "g"), (None, "null id", "en", "s", "h")]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def removed(texts, length):
    c = collections.Counter(t[i : i + length] for t in texts for i in range(len(t) - length + 1))
    out = []
    for t in texts:
        m = np.zeros(len(t) + 1, int)
        for i in range(len(t) - length + 1):
            if c[t[i : i + length]] > 1:
                m[i] += 1
                m[i + length] -= 1
        out.append(np.cumsum(m[:-1]) > 0)
    return out


@pytest.mark.parametrize("part", [2000, 1])
def test_suffix(spark, odd, empty, part):
    rows = odd.collect()
    texts = [(r.text or "").encode() for r in rows]
    want = sorted((r.doc_id or 0, len(t), int(m.sum()), hashlib.sha256(bytes(np.frombuffer(t, np.uint8)[~m])).hexdigest()) for r, t, m in zip(rows, texts, removed(texts, 400), strict=True))
    got = sorted((r.doc_id or 0, r.n_bytes, r.n_removed, r.kept_sha256) for r in suffix.repeats(odd, part=part).collect())
    assert got == want
    assert suffix.repeats(empty).count() == 0
    assert suffix.without_repeats(odd).columns == odd.columns


def test_suffix_meets_over_parts(spark):
    """A string of a dealt anchor that is single in one text index and stands twice or more in another."""
    r = np.random.default_rng(5)

    def word(n):
        return "".join(map(chr, r.integers(97, 123, n)))

    core = word(100)
    rows = []
    for i in range(12):
        tail = word(40) if i % 3 == 0 else tail  # three texts share a longer extension of the passage
        rows.append((i, word(60) + core + tail + word(60)))
    texts = [t.encode() for _, t in rows]
    want = [(i, int(m.sum())) for (i, _), m in zip(rows, removed(texts, 120), strict=True)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    for part in (1, 2, 3):
        assert sorted((x.doc_id, x.n_removed) for x in suffix.repeats(docs, 120, 16, part, target=0).collect()) == want


@pytest.mark.parametrize("bits", [24, 9])
def test_anchors_of_long_texts(monkeypatch, bits):
    """Positions of few bits stand for texts of many pieces."""
    monkeypatch.setattr(suffix, "_POS", np.uint64((1 << bits) - 1))
    r = np.random.default_rng(6)
    passage = r.integers(0, 26, 700, np.uint8) + 97
    data = np.concatenate([r.integers(0, 26, 333, np.uint8) + 97, passage, r.integers(0, 26, 5000, np.uint8) + 97, passage])
    a, doc = suffix.anchors(data, np.array([0, len(data)]), 400, 64)
    assert (doc == 0).all() and a["a"][0] == 0 and a["b"][-1] == len(data) - 400 and (a["a"][1:] == a["b"][:-1] + 1).all()
    own = np.repeat(a["h"], a["b"] - a["a"] + 1)
    assert (own[333 : 333 + 301] == own[-301:]).all()
    at = np.arange(len(data) - 63)
    h = bytescan.span_hash(bytescan.prefix_sums(data), at, at + 64)
    assert all(h[s : s + 337][np.argmin(h[s : s + 337] & ~suffix._POS)] == own[s] for s in range(0, len(own), 7))


def test_suffix_kernel():
    t = b"abcabcabcabcXYZabcabcabc\xffZabcabcabcabc\xff"
    hit = suffix.shared_starts(np.frombuffer(t, np.uint8), 9)
    c = collections.Counter(t[i : i + 9] for i in range(len(t) - 8))
    for i in range(len(t) - 8):
        if b"\xff" not in t[i : i + 9]:
            assert hit[i] == (c[t[i : i + 9]] > 1)


def test_simhash(spark, odd, empty):
    r = np.random.default_rng(0)
    x = r.integers(0, 1 << 62, 200).astype(np.uint64)
    x = np.unique(np.concatenate([x, x ^ np.uint64(5), x ^ np.uint64(1 << 40)]))
    got = {tuple(sorted(p)) for a, b in simhash.GrayIndex(x, np.zeros(len(x), np.int64)).links(2) for p in zip(a.tolist(), b.tolist(), strict=True)}
    d = np.bitwise_count(x[:, None] ^ x[None])
    assert got == {(i, j) for i, j in zip(*np.nonzero(d <= 2), strict=True) if i < j}
    rows = simhash.near_groups(odd, width=3).collect()
    assert len(rows) == odd.count()
    comp = {r.doc_id: r.component_id for r in rows}
    assert comp[4] == comp[3] == 3 and comp[1] == comp[2] == comp[7] == 1
    assert simhash.near_groups(empty).count() == 0
    kept = simhash.one_of_each(odd)
    assert kept.columns == odd.columns and {r.doc_id for r in kept.collect()} >= {3, 6}


def test_similar_beyond_the_radius(spark):
    """A repeated phrase moves a fingerprint of texts far, but not of sets; and no radius hides a similar pair."""
    r = np.random.default_rng(8)
    base = [f"w{x}" for x in r.integers(0, 10**9, 104)]
    rows = [(0, " ".join(base)), (1, " ".join(base + ["p q r s t"] * 50)), (2, " ".join(base[:60] + ["other"] * 44))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    sets = [simhash._set_of(t.encode(), 5, 42) for _, t in rows]
    fp = simhash.fingerprint_of([t.encode() for _, t in rows], 5, 42)
    assert len(np.intersect1d(sets[0], sets[1])) >= 0.8 * len(np.union1d(sets[0], sets[1])) and np.bitwise_count(fp[0] ^ fp[1]) > 20
    assert [x.component_id for x in simhash.similar_groups(docs).orderBy("doc_id").collect()] == [0, 0, 2]
    assert [x.component_id for x in simhash.similar_groups(docs, radius=0).orderBy("doc_id").collect()] == [0, 0, 2]
    own = [np.unique(np.concatenate([r.choice(a, n, replace=False), r.integers(1 << 40, 1 << 60, m)])).astype(np.uint64) for a in r.integers(0, 1 << 40, (9, 60)) for n, m in zip(r.integers(45, 61, 25), r.integers(0, 10, 25), strict=True)]
    cell = np.repeat(np.arange(3), 75)
    cols = [pa.array(cell), pa.array(simhash.majority(own).view(np.int64)), pa.array(np.arange(225)), pa.array([x.tobytes() for x in own], pa.binary())]
    got = simhash.forest(225, [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in simhash._similar_cells(0, 0.8)([pa.RecordBatch.from_arrays(cols, names=["cell", "fp", "name", "set"])])])
    both = np.array([[len(np.intersect1d(x, y)) for y in own] for x in own])
    size = np.array([len(x) for x in own])
    i, j = np.nonzero((both >= 0.8 * (size[:, None] + size - both)) & (cell[:, None] == cell))
    assert (got == simhash.forest(225, [(i, j)])).all() and 20 < len(np.unique(got)) < 220


def test_packing(spark, odd, empty):
    import public_tokenizers

    path = str(public_tokenizers.path("byte_bpe_50k.json"))
    e = packing.encoder(path)
    texts = [r.text or "" for r in odd.collect()] + ["don't we'll  'start\n\n x's", "ünï中😀", "a<|endoftext|>b"]
    assert [t.tolist() for t in e.encode(texts)] == [e.lib.encode(t, add_special_tokens=False).ids for t in texts]
    rows = packing.packed(packing.pieces(odd, path)).collect()
    bins = collections.defaultdict(list)
    for r in rows:
        bins[r.sequence_id].append((r.offset, r.length))
    for b in bins.values():
        at = 0
        for o, n in sorted(b):
            assert o == at
            at += n
        assert at <= packing.SEQUENCE
    assert packing.packed(packing.pieces(empty, path)).count() == 0
    size = np.random.default_rng(2).integers(1, 900, 300)
    best = packing.evolve(size.tolist(), 1024, 1)
    plain = packing.best_fit([], list(range(300)), size.tolist(), 1024)
    assert sorted(i for b in best for i in b) == list(range(300))
    assert packing.least_bins(size, 1024) <= len(best) <= len(plain)


def test_learned_scores(spark, odd):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    w = quality.train(docs, labels, epochs=4)
    got = quality.scored(odd, w).collect()
    assert len(got) == odd.count() and all(0 <= r.score <= 1 for r in got)
    same = [r.score for r in got if r.doc_id in (3, 4)]
    assert max(same) - min(same) < 1e-6
    text = np.frombuffer(("good text " * 200_000).encode(), np.uint8)
    assert abs(1 / (1 + np.exp(-quality._pooled(w, text))) - quality.score_texts(w, [text])[0]) < 1e-5
    assert quality.train(docs, labels.where("quality = 1"))["const"] == 1.0
    x = toxicity.train(docs, labels)
    rows = toxicity.scored(odd, x).collect()
    assert len(rows) == odd.count() and all(0 <= r.score <= 1 for r in rows)


def test_toxic_sentences_are_located(spark):
    bad = spark.createDataFrame([(i, f"Fine words here {i}. " + ("You rotter you. " if i % 2 else "") + "More fine words.", i % 2) for i in range(80)], "doc_id long, text string, toxic int")
    w = toxicity.train(bad, bad.select("doc_id", "toxic"))
    got = toxicity.locate(bad, w).collect()
    assert {r.doc_id for r in got} == set(range(1, 80, 2)) and all("rotter" in r.sentence for r in got)
    text = {r.doc_id: r.text.encode() for r in bad.collect()}
    found = {r.doc_id: [text[r.doc_id][s : s + n] for s, n in zip(r.offending_starts, r.offending_lengths, strict=True)] for r in toxicity.scored(bad, w).collect()}
    assert all((len(v) > 0) == (i % 2 == 1) and all(b"rotter" in x and b"Fine" not in x for x in v) for i, v in found.items())


def test_warc(spark, tmp_path):
    html = ["a" * 200, "b" * 200, "a" * 200, None, "", "short", "short", "a" * 200]
    pages = spark.createDataFrame([(i if i != 7 else None, f"http://x/{i} y", h, 1) for i, h in enumerate(html)], "page_id long, url string, html string, extra int")
    warc.write_archive(pages, f"file://{tmp_path}/w", roll=300)
    rows = {r.page_id: r for r in warc.read_archive(spark, f"file://{tmp_path}/w", with_body=True).collect()}
    assert len(rows) == 8
    assert rows[2].record_type == "revisit" and rows[2].refers_to == 0 and rows[None].refers_to == 0 and rows[6].record_type == "response"
    assert all(r.payload_digest == hashlib.sha256((html[i if i is not None else 7] or "").encode()).hexdigest() for i, r in rows.items())
    assert warc.page_of(warc._urn(-5, "ab" * 32)) == -5 and warc.page_of(warc._urn(1 << 60, "ab" * 32)) == 1 << 60


def test_warc_repeated_ids(spark, empty, tmp_path):
    """An id on several payloads: each payload is judged by itself and none is lost."""
    a, b = "A" * 300, "B" * 300
    rows = [(1, a), (5, a), (5, b), (None, b), (None, b), (5, None), (7, "x")]
    pages = spark.createDataFrame([(i, "u", h) for i, h in rows], "page_id long, url string, html string")
    warc.write_archive(pages, f"file://{tmp_path}/w")
    got = warc.read_archive(spark, f"file://{tmp_path}/w", with_body=True).collect()
    kinds = collections.Counter((r.page_id, r.payload_bytes, r.record_type, r.refers_to, bytes(r.body)[:1]) for r in got)
    assert kinds == {(1, 300, "response", None, b"A"): 1, (5, 300, "revisit", 1, b""): 1, (5, 300, "response", None, b"B"): 1, (None, 300, "revisit", 5, b""): 2, (5, 0, "response", None, b""): 1, (7, 1, "response", None, b"x"): 1}
    warc.write_archive(pages.limit(0), f"file://{tmp_path}/e")
    assert warc.read_archive(spark, f"file://{tmp_path}/e").count() == 0


def test_media(spark, odd, empty):
    for n in (*range(0, 400, 7), 31_991, 32_000, 64_001):
        p = bytes(range(256)) * (n // 256 + 1)
        back = media.demux(media.mux(p[:n]))
        assert b"".join(u[3] for u in back["units"]) == p[:n] and back["breaks"] == 0
    lost = bytearray(media.mux(b"x" * 2000))
    del lost[188 * 4 : 188 * 5]
    assert media.demux(bytes(lost))["breaks"] == 1
    units = media.access_units(media.with_stream(odd, "doc_id", "text")).groupBy("id").agg(F.count("*").alias("n")).count()
    assert units == odd.select("doc_id").distinct().count()


def test_rules(spark, odd, empty):
    def base(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        c, cov = collections.Counter(zip(w, w[1:], w[2:], strict=False)), set()
        for i in range(len(w) - 2):
            if c[tuple(w[i : i + 3])] > 1:
                cov |= {i, i + 1, i + 2}
        ls = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(ls) - len(set(ls)), len(cov)

    want = sorted((r.doc_id or 0, *base(r.text)) for r in odd.collect())
    got = rules.judged(odd).collect()
    assert sorted((r.doc_id or 0, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in got) == want
    assert all(not r.kept for r in got if r.base_failed)
    assert rules.judged(empty).count() == 0


@pytest.mark.parametrize("block", [4096, 2])
def test_lines(spark, odd, block):
    ws = [f"t{i}" for i in range(10)]
    rows = [(1, " ".join(ws)), (2, " ".join(ws[:9]) + "\nother line here"), (3, " ".join(ws[1:]) + " new\n\n" + "other line here"), (4, None), (5, "")]
    got = {r.doc_id: r for r in lines.line_decisions(spark.createDataFrame(rows, "doc_id long, text string"), block=block).collect()}
    assert got[1].removed == [] and got[2].removed == [0] and got[3].removed == [0, 2] and 4 not in got
    out = {r.doc_id: r.text for r in lines.without_repeats(odd).collect()}
    assert out[1] is None and out[4] == "" and out[3]


def test_pieces(spark, odd):
    import public_tokenizers
    import sentencepiece

    path = str(public_tokenizers.path("piece_bpe_32k.model"))
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    texts = [r.text or "" for r in odd.collect()] + ["  a  b\tc\x00", "ünï中😀", "the" * 100]
    got = pieces.encoder(path).encode(texts)
    assert [g.tolist() for g in got] == sp.encode(texts)
    rows = pieces.encoded(odd, path)
    assert all(r.round_trip for r in rows.collect())
    back = {r.doc_id: r.text for r in pieces.decoded(rows, path).collect()}
    assert back[6] == "one two three four five"


def test_hash_is_free_of_position():
    x = np.frombuffer(b"xxabcyyabc", np.uint8)
    h = bytescan.span_hash(bytescan.prefix_sums(x), np.array([2, 7]), np.array([5, 10]))
    assert h[0] == h[1]


def test_pipeline_stages(spark):
    import corpus_pipeline

    df = spark.read.parquet(f"{SF}/documents.parquet")
    cols = df.columns
    for name, stage in corpus_pipeline.STAGES[1:4]:
        df = stage(spark, df, SF)
        assert df.columns == cols, name
    assert df.count() > 0


def test_lines_free_their_disk(spark, monkeypatch):
    import os
    import time

    disk = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()
    before, real, held = disk.getAllFiles().size(), lines.settle, []

    def watched(df, name):
        if name == "marked":  # the largest table is gone before the postings move
            held.extend(os.path.exists(t._signgraph_path.removeprefix("file:")) for t in made["lines"])
        out = real(df, name)
        made.setdefault(name, []).append(out)
        return out

    made = {}
    monkeypatch.setattr(lines, "settle", watched)
    df = spark.range(400).select(F.col("id").alias("doc_id"), F.expr("concat('one two three four five ', id div 2, '\n', 'six seven eight nine ', id)").alias("text"))
    assert lines.line_decisions(df).count() == 400 and held == [False]
    deadline = time.time() + 10
    while disk.getAllFiles().size() > before + 30 and time.time() < deadline:  # count() above has a shuffle of its own
        time.sleep(0.1)
    assert disk.getAllFiles().size() <= before + 30


def test_lines_post_common_words_of_few_sets(spark, monkeypatch):
    n, real = [], lines._postings
    monkeypatch.setattr(lines, "_postings", lambda sets: n.append(sets.count()) or real(sets))
    df = spark.range(60).select(F.col("id").alias("doc_id"), F.expr("if(id < 5, 'most frequent words', concat_ws(' ', concat('a', id), concat('b', id), concat('c', id), 'most frequent words'))").alias("text"))
    assert lines.line_decisions(df, block=4).where("n_removed > 0").count() == 4
    assert n[0] == 56 and n[1] < 10  # the scan for common words leaves out sets whose prefix has none


def test_heads_of_words():
    data = np.frombuffer(b"a bb abcdefgh abcdefghi z", np.uint8)
    s, e = bytescan.runs(~bytescan.SPACE[data], np.array([0, len(data)]))
    want = [int.from_bytes(data[i:j].tobytes()[:8].ljust(8, b"\0"), "big") for i, j in zip(s, e, strict=True)]
    mix = bytescan.mix
    assert (lines._heads(data, s, e) == mix(np.array(want, np.uint64) ^ mix((e - s).astype(np.uint64)))).all()
