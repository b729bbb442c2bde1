"""Whole queries of the text operators against brute force; empty tables, clashing column names, bytes that are no text."""
import collections
import hashlib
import re

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

import corpus_pipeline
from signgraph.llm import lines, media, packing, pieces, quality, rules, simhash, suffix, toxicity, warc

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def rows(docs):
    return [(r.doc_id, r.text or "") for r in docs.collect()]


def least(ids, links):
    """The least id reachable from each."""
    up = {i: i for i in ids}

    def root(i):
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return i

    for a, b in links:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return {i: root(i) for i in ids}


def test_simhash_query(spark, rows):
    def fp(t):
        w = WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t))
        s = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([" ".join(w)] if w else [])
        h = np.array([xxhash.xxh64_intdigest(x.encode(), 42) for x in s], np.uint64)
        return sum(1 << b for b in range(64) if 2 * int((h >> np.uint64(b) & np.uint64(1)).sum()) > len(h)) if s else 0

    f = {i: fp(t) for i, t in rows}
    ids = sorted(f)
    comp = least(ids, [(a, b) for k, a in enumerate(ids) for b in ids[k + 1 :] if (f[a] ^ f[b]).bit_count() <= 2])
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in simhash.op2_simhash(spark, SF).collect()}
    assert got == {i: (f"{f[i]:016x}", comp[i]) for i in ids}


def test_suffix_query(spark, rows):
    count = collections.Counter(t.encode()[i : i + 400] for _, t in rows for i in range(len(t.encode()) - 399))
    want = {}
    for d, t in rows:
        t = t.encode()
        edge = np.zeros(len(t) + 1, int)
        for i in range(len(t) - 399):
            if count[t[i : i + 400]] > 1:
                edge[i] += 1
                edge[i + 400] -= 1
        hit = np.cumsum(edge[:-1]) > 0
        spans = int((np.diff(np.concatenate([[0], hit.astype(int)])) == 1).sum())
        want[d] = (len(t), int(hit.sum()), spans, hashlib.sha256(bytes(np.frombuffer(t, np.uint8)[~hit])).hexdigest())
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffix.op1_suffix_dedup(spark, SF).collect()}
    assert got == want and sum(x[1] > 0 for x in want.values()) > 5


def test_lines_query(spark, rows):
    every = [(d, k, frozenset(WORD.findall(x))) for d, t in sorted(rows) for k, x in enumerate(t.split("\n"))]
    every = [x for x in every if x[2]]
    sets = sorted({s for _, _, s in every}, key=len)
    by = collections.defaultdict(list)
    for i, s in enumerate(sets):
        for w in s:
            by[w].append(i)
    links = collections.defaultdict(set)
    for i, s in enumerate(sets):
        for j in {j for w in s for j in by[w] if j > i}:
            both = len(s & sets[j])
            if 5 * both >= 4 * (len(s) + len(sets[j]) - both):
                links[i].add(j)
                links[j].add(i)
    name = {s: i for i, s in enumerate(sets)}
    first, removed, total = {}, collections.defaultdict(list), collections.Counter()
    for d, k, s in every:
        i = name[s]
        total[d] += len(links[i])
        if i in first or any(j in first for j in links[i]):
            removed[d].append(k)
        first.setdefault(i, (d, k))
    got = {r.doc_id: (r.removed_lines, r.n_links, r.n_lines) for r in lines.op9_line_dedup(spark, SF).collect()}
    n = collections.Counter(d for d, _, _ in every)
    assert got == {d: (removed[d], total[d], n[d]) for d, _ in rows} and sum(map(len, removed.values())) > 5


@pytest.mark.parametrize("block,volume", [(3, 40), (4096, 60), (2, 1 << 20)])
def test_dealt_cells_lose_nothing(spark, block, volume):
    """Words in many sets and cells of many words are dealt in blocks; every link is counted once."""
    r = np.random.default_rng(block)
    pool = [f"w{i}" for i in range(14)]
    texts = [(i, " ".join(r.permutation(pool)[: int(r.integers(8, 14))]) + (" é\tü" if i % 3 else "")) for i in range(60)]
    want = collections.Counter()
    sets = {frozenset(t.split()) for _, t in texts}
    for s in sets:
        want[s] = sum(1 for o in sets if o != s and 5 * len(s & o) >= 4 * len(s | o))
    got = {x.doc_id: x.n_links for x in lines.line_decisions(spark.createDataFrame(texts, "doc_id long, text string"), block, volume).collect()}
    assert got == {i: want[frozenset(t.split())] for i, t in texts} and sum(got.values()) > 20


def test_words_are_compared_byte_by_byte(monkeypatch):
    """Hashes that all agree do not make words equal."""
    import pyarrow as pa

    monkeypatch.setattr(lines, "span_hash", lambda sums, s, e: np.zeros(len(s), np.uint64))
    w = lines.Words(pa.array([b"ab cd ", b"ab ce "]))
    assert w.code[0] == w.code[2] != w.code[1] and w.code[1] != w.code[3]


def jaccard_groups(rows):
    s = {i: {tuple(w[k : k + 5]) for k in range(len(w) - 4)} or ({tuple(w)} if w else set()) for i, t in rows if (w := WORD.findall(t.lower())) is not None}
    ids = sorted(s)
    return s, [(a, b) for k, a in enumerate(ids) for b in ids[k + 1 :] if (s[a] or s[b]) and 5 * len(s[a] & s[b]) >= 4 * len(s[a] | s[b])]


def test_near_stage_recall(docs, rows):
    _, links = jaccard_groups(rows)
    comp = {r.doc_id: r.component_id for r in simhash.similar_groups(docs).collect()}
    met = sum(comp[a] == comp[b] for a, b in links)
    assert len(links) > 5 and met >= 0.99 * len(links)


def test_gradient_is_the_slope(monkeypatch):
    r = np.random.default_rng(1)
    texts = [r.integers(97, 123, n).astype(np.uint8) for n in (5, 300, 900, 1500)]
    y, weight = np.array([0, 1, 1, 0], np.float32), np.ones(4, np.float32)
    w = {k: v.astype(np.float64) for k, v in quality.start_weights(3).items()}
    g, _ = quality._gradient(w, texts, y, weight)
    for k in ("o", "h", "a", "hb"):
        i = int(np.argmax(np.abs(g[k])))
        up, down = ({**w, k: w[k].copy()} for _ in range(2))
        up[k].flat[i] += 1e-4
        down[k].flat[i] -= 1e-4
        slope = (quality._gradient(up, texts, y, weight)[1] - quality._gradient(down, texts, y, weight)[1]) / 2e-4
        assert abs(slope - g[k].flat[i]) < 0.05 * abs(slope) + 1e-3


@pytest.mark.parametrize("n", [quality.PIECE - 3, quality.PIECE + 100, quality.PIECE + quality.HALF, quality.PIECE + quality.HALF + 1, 2 * quality.PIECE + 700])
def test_pieces_of_long_texts_score_as_the_whole(n):
    text = np.random.default_rng(n).integers(97, 123, n).astype(np.uint8)
    w = quality.start_weights(5)
    assert abs(quality._pooled(w, text) - float(quality.logits(w, [text])[0])) < 1e-5


def test_learned_operators_find_what_labels_mark(spark):
    sf = "/root/testdata/sf0.01"
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    q = quality.op4_byte_cnn(spark, sf).join(labels, "doc_id").where("held_out").select("quality", "score").collect()
    good, bad = [r.score for r in q if r.quality == 1], [r.score for r in q if r.quality == 0]
    assert np.mean([[(a > b) + 0.5 * (a == b) for b in bad] for a in good]) > 0.85
    t = toxicity.op6_toxicity_mil(spark, sf).join(labels, "doc_id").where("held_out").select("toxic", "score").collect()
    bad, good = [r.score for r in t if r.toxic == 1], [r.score for r in t if r.toxic == 0]
    assert np.mean([[(a > b) + 0.5 * (a == b) for b in good] for a in bad]) > 0.8


def test_rules_find_planted_outliers(spark):
    """Kept against the estimate in numpy: outliers go, the even ones stay, whatever the group."""
    r = np.random.default_rng(9)
    vocab = ["".join(map(chr, r.integers(97, 123, int(r.integers(3, 9))))) for _ in range(3000)]
    rows = [(i, " ".join(r.choice(vocab, int(r.integers(80, 200)))), "en", f"s{i % 2}") for i in range(600)]
    rows += [(1000 + i, " ".join(w + "#$%" for w in r.choice(vocab, 120)), "en", "s0") for i in range(20)]
    rows += [(2000 + i, "\n".join(["the same line again"] * 4 + [" ".join(r.choice(vocab, 120))]), "en", "s1") for i in range(20)]
    got = {x.doc_id: x.kept for x in rules.judged(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).collect()}
    assert all(got[i] for i in range(600)) and not any(got[1000 + i] for i in range(20))


def test_determinant_never_rises(spark):
    r = np.random.default_rng(2)
    x = np.concatenate([r.normal(size=(700, 4)), 8 + r.normal(size=(150, 4))])
    df = spark.createDataFrame([("a", *map(float, v)) for v in x], "g string, x0 double, x1 double, x2 double, x3 double")
    fit = rules.robust(df).where("g = 'a'").first()
    assert all(abs(fit[f"mu{i}"]) < 0.3 and 0.7 < fit["l00"] < 1.3 for i in range(4))


def test_media_is_damaged_and_named(spark):
    good = media.mux(b"x" * 1000)
    df = spark.createDataFrame([("a", good), ("b", good[:-7]), ("c", b"\0" + good[1:]), ("d", None)], "id string, media binary")
    got = collections.Counter((r.id, r.unit) for r in media.access_units(df).collect())
    assert got == {("a", 0): 1, ("b", -1): 1, ("c", -1): 1}


def test_empty_tables(spark, tmp_path):
    none = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    w = quality.train(none, labels)
    assert w == {"const": 0.5} and quality.scored(none, w).count() == 0 and quality.keep_good(none, w).count() == 0
    assert toxicity.scored(none, toxicity.train(none, labels)).count() == 0
    assert media.with_stream(none, "doc_id", "text").count() == 0
    assert lines.line_decisions(none).count() == 0 and lines.without_repeats(none).count() == 0
    assert rules.judged(none).count() == 0 and simhash.near_groups(none).count() == 0
    none.write.parquet(f"{tmp_path}/documents.parquet")
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    assert corpus_pipeline.run(spark, f"file://{tmp_path}").count() == 0
    import public_tokenizers

    assert pieces.encoded(none, str(public_tokenizers.path("piece_bpe_32k.model"))).count() == 0
    assert packing.packed(packing.pieces(none, str(public_tokenizers.path("byte_bpe_50k.json")))).count() == 0


def test_clashing_names_and_bytes(spark):
    """Columns named like the operators' own, null and repeated ids, a string column that holds no UTF-8."""
    names = ["_w", "_t", "_h", "_id", "_gone", "_tid", "_kept", "k", "r", "t", "gone", "sid", "tid", "cell", "comp", "h"]
    text = "one two three four five six seven eight nine ten"
    base = spark.createDataFrame([(1, text + "\n" + text), (1, text), (None, text), (2, None), (3, "")], "doc_id long, text string")
    df = base.select("doc_id", "text", *[F.lit(f"x{n}").alias(n) for n in names])
    for run in (lines.without_repeats, simhash.one_of_each, lambda d: suffix.without_repeats(d, 60)):
        out = run(df)
        assert out.columns == df.columns and all(r[n] == f"x{n}" for r in out.collect() for n in names)
    assert rules.judged(df.select("*", F.lit(None).cast("string").alias("lang"), F.lit("s").alias("source"))).count() == 5
    odd = spark.createDataFrame([(1, bytearray(b"ab \xff\xfe cd " * 30)), (2, bytearray(b"ab \xff\xfe cd " * 30))], "doc_id long, b binary").select("doc_id", F.col("b").cast("string").alias("text"))
    assert lines.line_decisions(odd).count() == 2


def test_one_very_long_text(spark):
    long = "\n".join(" ".join(f"w{(i * 7 + k) % 5003}" for k in range(40)) for i in range(3000))
    df = spark.createDataFrame([(1, long, "en", "s"), (2, long[:5000] + " x", "en", None), (3, "short", None, "s")], "doc_id long, text string, lang string, source string")
    got = {r.doc_id: r for r in lines.line_decisions(df).collect()}
    assert got[1].n_lines == 3000 and got[2].n_removed > 5
    assert rules.judged(df).count() == 3 and simhash.near_groups(df).count() == 3
    assert {r.doc_id: r.n_removed for r in suffix.repeats(df).collect()}[2] > 4000


def test_warc_reads_back_what_it_wrote(spark):
    got = warc.op5_warc(spark, SF)
    assert got.count() == spark.read.parquet(f"{SF}/pages.parquet").count()
