"""Each operator against brute force, a round trip or held-out accuracy, with awkward rows."""

import hashlib
import itertools
import random
import zlib

import numpy as np
import pytest
import xxhash

tokenizers = pytest.importorskip("tokenizers")
public = pytest.importorskip("public_tokenizers")

from treewalk.llm import chunk_bpe, decontaminate, language, quality, revisit, simhash, suffix_dedup, token_file, toxicity, vector_graph  # noqa: E402

SCHEMA = "doc_id long, text string, lang string, source string, fp long, row long"
rnd = random.Random(3)
words = lambda n, seed=0: " ".join(random.Random(seed).choice("alpha beta gamma delta the of and é ünder naïve 12 3x".split()) + str(random.Random(seed * 7 + i).randint(0, 99)) for i in range(n))
PASSAGE = words(60, 5)
ROWS = [
    (0, words(40, 1) + "\n" + PASSAGE), (1, PASSAGE + " " + words(30, 2)), (2, None), (3, ""), (4, "   \n\t"), (5, words(900, 4)), (6, words(40, 1) + "\n" + PASSAGE),
    (7, "it's <|endoftext|> 日本語 ×" + "x" * 3000), (8, "a" * 700), (9, words(3, 9)), (10, "One"), (11, "one"), (12, "İ ǅ é ​"),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, "en", "s", 1, 2) for i, t in ROWS], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def awkward(spark):
    """Null and repeated ids."""
    return spark.createDataFrame([(None, "some words here", "en", "s", 1, 2), (1, "more words", "en", "s", 1, 2), (1, None, "en", "s", 1, 2)], SCHEMA)


def test_chunk_bpe_equals_library(docs, empty, awkward):
    path = public.path("word_bpe_49k.json")
    tok = tokenizers.Tokenizer.from_file(path)
    got = {r.doc_id: r for r in chunk_bpe.digests(docs, path).collect()}
    for i, t in ROWS:
        ids = tok.encode(t or "", add_special_tokens=False).ids
        assert got[i].n_tokens == len(ids) and got[i].ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), i
        assert got[i].decoded_sha256 == hashlib.sha256(tok.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    assert chunk_bpe.digests(empty, path).count() == 0
    assert sorted(r.n_tokens for r in chunk_bpe.digests(awkward, path).collect()) == [0, 2, 3]
    back = {r.doc_id: r.text for r in chunk_bpe.decode(chunk_bpe.encode(docs, path), path).collect()}
    assert back[10] == "one</w>"


def test_chunk_joins_are_repaired(spark, monkeypatch):
    """Long texts without a space at their cuts."""
    path = public.path("word_bpe_49k.json")
    tok = tokenizers.Tokenizer.from_file(path)
    texts = ["".join(random.Random(k).choice("abcde fg") for _ in range(120_000)) for k in range(2)] + ["".join(random.Random(9).choice("abcdefg") for _ in range(90_000))]
    d = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string")
    for r in chunk_bpe.digests(d, path).collect():
        ids = tok.encode(texts[r.doc_id], add_special_tokens=False).ids
        assert r.n_joins > 0 and r.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()


def test_chunks_of_shared_passages_are_reused(spark):
    """A passage that different texts share is cut and encoded alike in all of them."""
    r = random.Random(5)
    prose = lambda n: " ".join("".join(r.choice("abcdefgh") for _ in range(r.randint(2, 9))) for _ in range(n))
    passage = prose(6000)
    texts = [prose(r.randint(50, 400)) + " " + passage + " " + prose(r.randint(50, 400)) for _ in range(12)]
    d = spark.createDataFrame([(k, t) for k, t in enumerate(texts)], "doc_id long, text string").repartition(4)
    got = chunk_bpe.reuse(d).first()
    assert got.shared_chunks >= 2 and got.distinct_chunks < 0.8 * got.chunks
    real = chunk_bpe.reuse(spark.read.parquet("/root/testdata/sf0.1/documents.parquet")).first()
    assert real.shared_chunks > 0 and real.distinct_chunks < real.chunks
    path = public.path("word_bpe_49k.json")
    tok = tokenizers.Tokenizer.from_file(path)
    for x in chunk_bpe.digests(d, path).collect():
        ids = tok.encode(texts[x.doc_id], add_special_tokens=False).ids
        assert x.n_joins > 0 and x.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()


def test_token_files_round_trip(spark, docs, empty, awkward):
    path = public.path("byte_bpe_50k.json")
    tok = tokenizers.Tokenizer.from_file(path)
    manifest = token_file.write(docs, path, "file:///tmp/treewalk-test-tokens-" + str(rnd.random()))
    got, full, start = {r.doc_id: r for r in token_file.digests(manifest).collect()}, {r.doc_id: r for r in token_file.read(manifest).collect()}, 0
    for i, t in ROWS:
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 0]
        assert (got[i].start, got[i].n_tokens, got[i].ids_crc32) == (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())) and list(full[i].ids) == ids
        start += len(ids)
    assert token_file.run(spark, empty, path).count() == 0 and token_file.run(spark, awkward, path).count() == 3


@pytest.mark.parametrize("high", [1, 2, 300, 50_000, 1 << 31, 1 << 63])
@pytest.mark.parametrize("n", [0, 1, 7, 1023, 1024, 1025, 4000])
def test_simple8b(n, high):
    v = np.random.default_rng(n).integers(0, high, n, dtype=np.uint64)
    v[n // 3 : n // 2] = 0
    if n > 10:
        v[5] = 2**64 - 1
    w, per = token_file.pack(v)
    assert np.array_equal(token_file.unpack(w, per, n), v)


def _fp(t):
    w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "").encode().split()
    s = [b" ".join(w[k : k + 3]) for k in range(len(w) - 2)] if len(w) >= 3 else [b" ".join(w)] if w else []
    h = [xxhash.xxh64_intdigest(x, 42) for x in s]
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))


def test_simhash_brute_force(docs, empty, awkward):
    got = {r.doc_id: r for r in simhash.group(docs).collect()}
    fp = {i: _fp(t) for i, t in ROWS}
    comp = {i: i for i in fp}
    for _ in fp:
        comp = {i: min(comp[j] for j in fp if bin(fp[i] ^ fp[j]).count("1") <= 2) for i in fp}
    for i in fp:
        assert got[i].fingerprint == f"{fp[i]:016x}" and got[i].component_id == comp[i]
    assert simhash.group(empty).count() == 0 and simhash.group(awkward).count() == 3


def _jaccard(a, b):
    s, t = ({tuple(x[k : k + 5]) for k in range(len(x) - 4)} for x in (a.lower().split(), b.lower().split()))
    return len(s & t) / len(s | t)


def test_simhash_representatives(spark, empty):
    """Copies with scattered changes at five-word similarities of 0.8 and more go; others stay."""
    r = random.Random(12)
    rows, copies = [], []
    for k in range(120):
        base = [f"w{r.randint(0, 400)}" for _ in range(r.randint(80, 300))]
        rows.append((k, " ".join(base)))
        for c in range(2):
            changed = list(base)
            for i in r.sample(range(len(base)), max(1, len(base) // 60)):
                changed[i] = "other" + str(r.random())
            text = " ".join(changed).upper()
            if _jaccard(rows[k][1], text) >= 0.8:
                copies.append((1000 + 2 * k + c, text))
    crowd = [f"c{i}" for i in range(200)]
    crowded = [(2000 + k, " ".join([*crowd[:50], f"x{k}", *crowd[50:]])) for k in range(150)]
    d = spark.createDataFrame([(i, t, 5, 6) for i, t in rows + copies + crowded], "doc_id long, text string, _kept int, _row int").repartition(3)
    out = simhash.representatives(d)
    kept = {x.doc_id for x in out.collect()}
    assert out.columns == d.columns and len(copies) > 100
    assert kept >= set(range(120)) and 2000 in kept and len([i for i in kept if i >= 2000]) == 1
    assert len([i for i, _ in copies if i in kept]) <= 0.1 * len(copies)
    twice = spark.createDataFrame([(None, "some words here", 1), (1, "more words", 1), (1, "more words", 2), (1, None, 3), (2, "", 4)], "doc_id long, text string, _row int")
    assert sorted(x._row for x in simhash.representatives(twice).collect()) in ([1, 1, 3], [1, 2, 3], [1, 1, 4], [1, 2, 4])
    assert simhash.representatives(empty).count() == 0


@pytest.mark.parametrize("n", [30, 400])
def test_simhash_wide_bucket(n):
    g = np.random.default_rng(n)
    base = g.integers(0, 1 << 63, (3, 2), dtype=np.uint64)
    f = base[g.integers(0, 3, n)] ^ (np.uint64(1) << g.integers(0, 63, (n, 2)).astype(np.uint64)) ^ (np.uint64(1) << g.integers(0, 63, (n, 2)).astype(np.uint64))
    home = g.random(n) < 0.7
    far = np.bitwise_count(f[:, None] ^ f[None]).sum(2)
    for limit in (3, 6):
        child, parent = simhash.link_wide(f, home, limit)
        a, b = np.nonzero((far <= limit) & home[:, None])
        want, got = np.arange(n), np.arange(n)
        for label, (x, y) in ((want, (a, b)), (got, (child, parent))):
            for _ in range(n):
                before = label.copy()
                np.minimum.at(label, x, label[y])
                np.minimum.at(label, y, label[x])
                if np.array_equal(before, label):
                    break
        assert np.array_equal(want, got)


def test_simhash_wide_pairs_meet():
    """Every pair within the limit of 23 of 128 bits meets at an anchor, and is linked there."""
    g = np.random.default_rng(3)
    assert simhash.link_limit(0.8) == 23
    for k in range(300):
        bits = np.zeros(128, np.uint8)
        bits[g.choice(128, 23, replace=False)] = 1
        if not k:  # the worst case: evenly over the blocks
            bits = np.zeros((8, 16), np.uint8)
            bits[:, :3] = 1
            bits[7, 2] = 0
            bits = bits.reshape(-1)
        x = g.integers(0, 1 << 63, 2, dtype=np.uint64)
        f = np.stack([x, x ^ np.packbits(bits, bitorder="little").view(np.uint64)])
        found = [simhash.wide_anchors(f, b) for b in range(8)]
        key, row = (np.concatenate([p[c] for p in found]) for c in (0, 1))
        order = np.argsort(key, kind="stable")
        assert set(key[row == 0]) & set(key[row == 1])
        assert len(simhash.link_runs(key[order], f[row[order]], 23)[0])


def test_simhash_runs():
    """Small and large runs at once, against all pairs of each run."""
    g = np.random.default_rng(4)
    key = np.sort(np.concatenate([g.integers(0, 60, 300), np.full(200, 7)]))
    base = g.integers(0, 1 << 63, (4, 2), dtype=np.uint64)
    f = base[g.integers(0, 4, len(key))] ^ (np.uint64(1) << g.integers(0, 63, (len(key), 2)).astype(np.uint64))
    far = np.bitwise_count(f[:, None] ^ f[None]).sum(2)
    a, b = np.nonzero((far <= 3) & (key[:, None] == key[None]))
    want, got = np.arange(len(key)), np.arange(len(key))
    for label, (x, y) in ((want, (a, b)), (got, simhash.link_runs(key, f, 3))):
        for _ in key:
            before = label.copy()
            np.minimum.at(label, x, label[y])
            np.minimum.at(label, y, label[x])
            if np.array_equal(before, label):
                break
    assert np.array_equal(want, got)


@pytest.mark.parametrize("n", [20, 200])
def test_simhash_bucket(n):
    r = np.random.default_rng(n)
    base = r.integers(0, 1 << 63, 4, dtype=np.uint64)
    x = np.unique(np.concatenate([base, [base[i % 4] ^ np.uint64(1 << int(r.integers(64))) ^ np.uint64(1 << int(r.integers(64))) ^ np.uint64(1 << int(r.integers(64))) for i in range(n)]]).astype(np.uint64))
    near = np.bitwise_count(x[:, None] ^ x[None, :]) <= 2
    want = np.arange(len(x))
    for _ in range(len(x)):
        want = np.array([want[near[i]].min() for i in range(len(x))])
    child, parent = simhash.link_bucket(x)
    got = np.arange(len(x))
    got[child] = parent
    assert len({(a, b) for a, b in zip(want, got)}) == len(set(want)) == len(set(got))


def _suffix_brute(rows):
    b = {i: (t or "").encode() for i, t in rows}
    n = {}
    for x in b.values():
        for k in range(len(x) - 199):
            n[x[k : k + 200]] = n.get(x[k : k + 200], 0) + 1
    out = {}
    for i, x in b.items():
        m = np.zeros(len(x), bool)
        for k in range(len(x) - 199):
            if n[x[k : k + 200]] > 1:
                m[k : k + 200] = True
        out[i] = (len(x), int(m.sum()), int((np.diff(np.concatenate([[0], m.astype(int)])) == 1).sum()), hashlib.sha256(bytes(np.frombuffer(x, np.uint8)[~m])).hexdigest())
    return out


@pytest.mark.parametrize("crowd", [suffix_dedup.CROWD, 2])
def test_suffix_brute_force(spark, docs, empty, awkward, crowd):
    r = random.Random(8)
    text = lambda n: "".join(r.choice("abcdefgh é") for _ in range(n))
    p, q = text(260), text(170)
    extra = [(100 + k, t) for k, t in enumerate([text(300) + p + text(50), text(20) + p[:230] + text(400), p[30:] + text(10), q + text(100), text(10) + q, text(90) + p[5:215] + text(9), *[text(30) + p + text(40) for _ in range(6)]])]
    rows = ROWS + extra
    d = spark.createDataFrame([(i, t) for i, t in rows], "doc_id long, text string").repartition(3)
    got = {x.doc_id: (x.n_bytes, x.n_removed, x.n_spans, x.kept_sha256) for x in suffix_dedup.digests(d, crowd).collect()}
    assert got == _suffix_brute(rows)
    assert suffix_dedup.digests(empty).count() == 0 and suffix_dedup.digests(awkward).count() == 3
    assert suffix_dedup.clean(docs).columns == docs.columns


def test_decontamination(spark, docs, empty, awkward):
    item = " ".join(f"term{k}" for k in range(20))
    changed = item.replace("term9 ", "other ")  # one substitution
    short = "tiny unique marker"
    rows = [(0, words(30, 1) + " " + item + " " + words(5, 2)), (1, words(9, 3) + ". " + changed.upper()), (2, words(50, 4)), (3, " ".join(item.split()[:9])), (4, None), (5, "x " + short + " y"), (6, "")]
    d = spark.createDataFrame([(i, t, "z") for i, t in rows], "doc_id long, text string, item_id string")
    b = spark.createDataFrame([(7, item), (8, short), (9, None), (7, item)], "item_id long, text string")
    got = {r.doc_id: (r.contaminated, list(r.item_ids)) for r in decontaminate.flag(d, b).collect()}
    assert got == {0: (True, [7]), 1: (True, [7]), 2: (False, []), 3: (False, []), 4: (False, []), 5: (True, [8]), 6: (False, [])}
    assert {r.doc_id for r in decontaminate.clean(d, b).collect()} == {2, 3, 4, 6}
    own = spark.createDataFrame([(None, item, 1), (None, "clean text", 2), (3, item, 3), (3, "clean text too", 4)], "doc_id long, text string, _row int")
    assert sorted((x.doc_id or 0, x.contaminated) for x in decontaminate.flag(own, b).collect()) == [(0, False), (0, True), (3, False), (3, True)]
    assert sorted(x._row for x in decontaminate.clean(own, b).collect()) == [2, 4]
    none = spark.createDataFrame([], "item_id long, text string")
    assert decontaminate.flag(d, none).where("contaminated").count() == 0 and decontaminate.flag(empty, b).count() == 0 and decontaminate.flag(awkward, b).count() == 3


def test_decontamination_oracle(spark):
    """The registered query against its SQL, with planted passages that hold changed words."""
    import duckdb

    from treewalk.llm import queries

    sf = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want = sorted(con.execute(decontaminate.ORACLE).fetchall())
    got = sorted(tuple(r) for r in queries.op5_decontaminate(spark, sf).collect())
    assert got == want and any(r[1] for r in got)


@pytest.mark.parametrize("n", [13, 14])
def test_decontamination_replacements(spark, n):
    """Items of 13 and 14 words with one to three words replaced, against the verifier alone."""
    item = [f"term{k}" for k in range(n)]
    cases = [c for m in (1, 2, 3) for c in itertools.combinations(range(n), m)]
    rows = [(k, "some words " + " ".join("other" if i in c else w for i, w in enumerate(item)) + " behind it") for k, c in enumerate(cases)]
    span, agree = decontaminate.SPAN, decontaminate.AGREE
    want = {k for k, c in enumerate(cases) if any(span - sum(lo <= i < lo + span for i in c) >= agree for lo in range(n - span + 1))}
    d = spark.createDataFrame(rows, "doc_id long, text string")
    b = spark.createDataFrame([(7, " ".join(item))], "item_id long, text string")
    assert {r.doc_id for r in decontaminate.flag(d, b).where("contaminated").collect()} == want


def _labelled(n):
    r = random.Random(1)
    rows = []
    for k in range(n):
        bad, toxic = k % 4 == 0, k % 5 == 0
        w = [f"w{r.randint(0, 60)}" for _ in range(40)]
        if toxic:
            w[r.randint(0, 39)] = r.choice(["grumpf", "blarg"])
        rows.append((k, (" ".join(x.upper() + "!!" for x in w) if bad else " ".join(w)), int(not bad), int(toxic)))
    return rows


def test_quality_and_toxicity(spark, empty, awkward):
    rows = _labelled(600)
    docs = spark.createDataFrame([(i, t) for i, t, _, _ in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(i, q, x) for i, _, q, x in rows], "doc_id long, quality int, toxic int")
    for module, column, at in ((quality, "quality", 2), (toxicity, "toxic", 3)):
        net = module.fit(docs, labels.select("doc_id", column))
        got = {r.doc_id: r for r in module.score(docs, net).collect()}
        held = [i for i in got if got[i].held_out]
        assert held and all(got[i].held_out == (zlib.crc32(str(i).encode()) % 5 == 0) for i in got)
        assert np.mean([got[i].predicted == rows[i][at] for i in held]) > 0.95
        assert module.score(empty, net).count() == 0 and all(0 <= r.score <= 1 for r in module.score(awkward, net).collect())
        assert module.fit(docs, labels.select("doc_id", column).limit(0)) is None and module.score(awkward, None).count() == 3
    assert toxicity.keep(docs, net).columns == docs.columns


@pytest.mark.parametrize("name", ["quality", "toxicity"])
def test_gradients(name):
    """Each net's gradients against differences of its loss, in double precision."""
    g = np.random.default_rng(3)
    if name == "quality":
        net, count, y = quality.Net(), np.array([2, 0, 3, 1]), np.array([1.0, 0.0, 0.0, 1.0])
        x, weight = g.standard_normal((6, quality.FEATURES)), np.ones(4)
        forward, gradients = lambda: net._forward(x, count)[0], lambda: net.gradients(x, count, y)
    else:
        net, y, weight = toxicity.Net(), np.array([1.0, 0.0, 1.0]), np.array([1.0, 2.0, 0.5])
        x, mask = g.standard_normal((3, 5, toxicity.INPUTS)), np.array([[1, 1, 1, 1, 1], [1, 1, 1, 0, 0], [1, 0, 0, 0, 0]], bool)
        forward, gradients = lambda: net.forward(x, mask)[0], lambda: net.gradients(x, mask, y, weight)
    net.p = {k: v.astype(float) for k, v in net.p.items()}

    def loss():
        out = forward()
        return float((-(y * np.log(out) + (1 - y) * np.log(1 - out)) * weight).sum() / weight.sum())

    for k, got in gradients().items():
        flat = net.p[k].reshape(-1)
        for at in g.choice(len(flat), min(6, len(flat)), replace=False):
            kept = flat[at]
            flat[at] = kept + 1e-4
            up = loss()
            flat[at] = kept - 1e-4
            down = loss()
            flat[at] = kept
            assert abs((up - down) / 2e-4 - np.asarray(got).reshape(-1)[at]) < 2e-3, (k, at)


def test_language_mixture_brute_force():
    """Two languages: the proportion found has the likelihood of the best on a grid."""
    r = random.Random(6)
    text = lambda s, n: " ".join("".join(r.choice(s) for _ in range(3)) for _ in range(n))
    one, two = "ba be bi bo bu".split(), "be xo xy zu zy".split()
    counts = np.array([np.bincount(language.grams(text(s, 3000)), minlength=language.BUCKETS) for s in (one, two)])
    model = language.Model(["aa", "bb"], counts)
    for n in (30, 80, 120):
        c = model.profile(text(one, n) + " " + text(two, 120 - n + 20)).astype(float)
        theta = model.mixture(c[None, :])[0]
        like = lambda t: float((c * np.log(np.maximum(np.array([t, 1 - t]) @ model.like.T, 1e-30))).sum())
        best = max(np.linspace(0, 1, 201), key=like)
        assert abs(theta[0] - best) < 0.05


def test_long_repeated_and_extra(spark):
    """Very long texts, repeated rows and clashing columns in the scoring operators."""
    long = " ".join(f"w{k % 97}" for k in range(60_000))
    d = spark.createDataFrame([(1, long, 0.1, 9), (1, long, 0.2, 9), (2, "short", 0.3, 9), (None, None, 0.4, 9)], "doc_id long, text string, score double, held_out int")
    rows = _labelled(300)
    docs = spark.createDataFrame([(i, t) for i, t, _, _ in rows], "doc_id long, text string")
    for module, column, at in ((quality, "quality", 2), (toxicity, "toxic", 3)):
        net = module.fit(docs, spark.createDataFrame([(r[0], r[at]) for r in rows], f"doc_id long, {column} int"))
        got = module.score(d, net).collect()
        assert len(got) == 4 and len({r.score for r in got if r.doc_id == 1}) == 1
    model = language.fit(docs.selectExpr("doc_id", "text", "'xx' AS lang"))
    assert sorted(r.lang_pred for r in language.predict(d, model).collect()) == ["und", "xx", "xx", "xx"]


def test_language(spark, empty, awkward):
    r = random.Random(2)
    syllables = {"aa": "ba be bi bo bu".split(), "bb": "xo xy zu zy qa".split()}
    rows = [(k, " ".join("".join(r.choice(syllables["aa" if k % 2 else "bb"]) for _ in range(3)) for _ in range(30)), "aa" if k % 2 else "bb") for k in range(200)] + [(900, "123 !?", "aa"), (901, None, "bb"), (902, "", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language.fit(docs)
    got = {x.doc_id: x for x in language.predict(docs, model).collect()}
    assert all(got[i].lang_pred == lang for i, t, lang in rows if i < 900) and all(got[i].lang_pred == "und" for i in (900, 901, 902))
    mixed = rows[0][1] + " " + rows[1][1]
    m = language.predict(spark.createDataFrame([(1, mixed)], "doc_id long, text string"), model).first()
    assert set(m.mixture) == {"aa", "bb"} and abs(m.mixture["aa"] - 0.5) < 0.15
    assert language.predict(empty, model).count() == 0 and language.predict(awkward, language.fit(empty)).where("lang_pred = 'und'").count() == 3


def test_language_of_eight():
    """A text in eight languages is not cut to six."""
    r = random.Random(4)
    letters = ["bcd", "fgh", "jkl", "mnp", "qrs", "tvw", "xyz", "aei"]
    text = lambda k: " ".join("".join(r.choice(letters[k]) for _ in range(6)) for _ in range(60))
    counts = np.array([np.bincount(language.grams(" ".join(text(k) for _ in range(20))), minlength=language.BUCKETS) for k in range(8)])
    model = language.Model([f"l{k}" for k in range(8)], counts)
    theta = model.mixture(np.array([model.profile(" ".join(text(k) for k in range(8)))]))[0]
    assert (theta > 0.05).sum() == 8


def test_vectors(spark):
    r = np.random.default_rng(5)
    base = r.standard_normal((150, 16))
    x = np.concatenate([base, base[:40] + 0.08 * r.standard_normal((40, 16)), base[:1] + 0.02 * r.standard_normal((80, 16)), base[5:6], base[5:6] * 2])
    rows = [(k, v.tolist(), 1) for k, v in enumerate(x)] + [(500, None, 1), (501, [0.0] * 16, 1), (502, [float("nan")] * 16, 1), (503, [None] * 16, 1), (504, [1.0], 1)]
    d = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").repartition(3)
    out, _ = vector_graph.link(d, slice_size=60)
    got = {g.vec_id: g for g in out.collect()}
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    near = u @ u.T >= 0.9
    truth = near.sum(1) - 1
    found = np.array([got[k].n_links for k in range(len(x))])
    assert (found <= truth).all() and found.sum() >= 0.97 * truth.sum()
    assert all(got[k].n_links == 0 and got[k].component_id == k and got[k].kept for k in range(500, 505)) and len(got) == len(rows)
    assert vector_graph.audit(d.where("vec_id < 500"), out) >= 0.9
    assert vector_graph.run(d.limit(0)).count() == 0


def test_vector_groups_above_candidates(spark):
    """Many groups of more distinct near copies than a node has candidates, in one slice."""
    r = np.random.default_rng(6)
    base = r.standard_normal((20, 64))
    x = np.concatenate([b + 0.24 * r.standard_normal((100, 64)) for b in base])
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    index = vector_graph.Searcher(u, vector_graph.build(u), 0.9)
    near = u @ u.T >= 0.9
    assert near.sum() > 20 * 100 * 50
    found = dict(index.queries(u))
    assert all(np.array_equal(np.sort(found[k]), np.flatnonzero(near[k])) for k in range(len(u)))
    d = spark.createDataFrame([(k, v.tolist(), 1) for k, v in enumerate(x)], "vec_id long, embedding array<double>, label int").repartition(3)
    got = {g.vec_id: g.n_links for g in vector_graph.link(d)[0].collect()}
    assert [got[k] for k in range(len(x))] == (near.sum(1) - 1).tolist()


def test_vector_links_across_shards(spark):
    """Pairs just above the limit, many shards, few dimensions: every link against brute force."""
    r = np.random.default_rng(7)
    x = r.standard_normal((1500, 8))
    x = np.concatenate([x, x[:500] + 0.35 * r.standard_normal((500, 8))])
    d = spark.createDataFrame([(k, v.tolist(), 1) for k, v in enumerate(x)], "vec_id long, embedding array<double>, label int").repartition(3)
    got = {g.vec_id: g.n_links for g in vector_graph.link(d, slice_size=60, share=1.0)[0].collect()}
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    assert [got[k] for k in range(len(x))] == ((u @ u.T >= 0.9).sum(1) - 1).tolist()


def test_vector_leaves_and_calibration(spark):
    """Shards with leaves of their own, with the full bound: no link lost.  Calibrated routing over
    sets of few and of many dimensions: the audit's recall holds against brute force."""
    r = np.random.default_rng(9)
    flat = r.standard_normal((1200, 8))
    tight = np.concatenate([r.standard_normal((900, 64)), np.repeat(r.standard_normal((30, 64)), 10, 0) + 0.1 * r.standard_normal((300, 64))])
    for x in (flat, tight):
        d = spark.createDataFrame([(k, v.tolist(), 1) for k, v in enumerate(x)], "vec_id long, embedding array<double>, label int").repartition(3)
        u = x / np.linalg.norm(x, axis=1, keepdims=True)
        truth = (u @ u.T >= 0.9).sum(1) - 1
        got = {g.vec_id: g.n_links for g in vector_graph.link(d, slice_size=60, share=1.0, max_shards=5)[0].collect()}
        assert [got[k] for k in range(len(x))] == truth.tolist()
        out = vector_graph.link(d, slice_size=60)[0].collect()
        got = {g.vec_id: g.n_links for g in out}
        assert out[0].audit_recall >= 0.99 and sum(got.values()) >= 0.99 * truth.sum() > 0


def test_revisits(spark):
    schema = "record_id long, record_type string, url string, ts long, status int, etag string, last_modified string, headers map<string,string>, extra int"
    rows = [
        (1, "response", "http://a.com/x/", 10, 200, '"1"', "d", {"content-length": "5", "server": "p"}, 0),
        (2, "response", "https://A.com:443/x#f", 20, 200, '"2"', "d", {"content-length": "6"}, 0),
        (3, "revisit", "https://www.a.com/x?utm_source=q", 30, 304, 'W/"2"', None, {"content-length": "0", "date": "z"}, 0),
        (4, "revisit", "http://a.com/x", 15, 304, '"2"', None, None, 0),
        (5, "revisit", "http://a.com/x", 10, 304, '"1"', None, None, 0),
        (6, "revisit", "http://a.com/x", 99_999, 304, None, "d", {}, 0),
        (7, "revisit", None, 30, 304, None, None, None, 0),
        (8, "revisit", "http://a.com/x", 21, 304, None, None, None, 0),
    ]
    d = spark.createDataFrame(rows, schema)
    for width in (4096, 7):
        got = {r.record_id: (r.verdict, r.resolved_id) for r in revisit.resolve(d, width).collect()}
        assert got == {3: ("match", 2), 4: ("mismatch", None), 5: ("no_response", None), 6: ("match", 2), 7: ("no_response", None), 8: ("no_validator", 2)}
    assert {r.record_id: r.headers for r in revisit.resolve(d).collect()}[3] == {"content-length": "6", "date": "z"}
    assert revisit.resolve(d.limit(0)).count() == 0


def test_pipeline_stages(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    n, columns = docs.count(), docs.columns
    from treewalk.llm.common import cut

    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = cut(stage(spark, docs, sf), name)
        assert docs.columns == columns and docs.count() <= n, name
        n = docs.count()
    assert corpus_pipeline.STAGES[-1][1](spark, docs, sf).count() == n > 0


def test_pipeline_stages_with_awkward_rows(spark):
    """Nulls, repeated ids, clashing names and empty tables pass every stage."""
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    schema = "doc_id long, text string, lang string, source string, n_chars long, _row int, _key int, _kept int, _text int, row int"
    few = [(None, None, None, None, None, 1, 1, 1, 1, 1), (None, "plain words of some kind", "en", "a", 24, 2, 2, 2, 2, 2), (7, "another text that stays", "en", None, 23, 3, 3, 3, 3, 3), (7, "and one more under the same id", "en", "b", 30, 4, 4, 4, 4, 4), (8, "", "en", "b", 0, 5, 5, 5, 5, 5)]
    for rows, left in ((few, {2, 3, 4}), ([], set())):
        d = spark.createDataFrame(rows, schema)
        for name, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, d, sf)
            assert out.columns == d.columns, name
            assert {r._row for r in out.collect()} >= left, name
        assert corpus_pipeline.STAGES[-1][1](spark, d, sf).count() == len(rows)


def _peak(job):
    """Bytes that Python and numpy held at most, and the result."""
    import tracemalloc

    tracemalloc.start()
    try:
        out = job()
        return tracemalloc.get_traced_memory()[1], out
    finally:
        tracemalloc.stop()


def test_driver_holds_little_of_what_it_samples(spark):
    """The sample of anchors stays in Arrow but for common keys; a fit holds its texts' numbers in 32 bits."""
    head = "".join(random.Random(1).choices("abcdefghij ", k=300))
    texts = ["".join(random.Random(k).choices("abcdefghij ", k=6000)) + head + chr(97 + k % 26) * 3 + str(k) * 100 for k in range(300)]
    rows = spark.createDataFrame(list(enumerate(texts)), "row long, text string").repartition(3)
    peak, cuts = _peak(lambda: suffix_dedup._splits(rows, 20))
    assert cuts
    assert peak < 20e6
    fitted = [(t, int(k % 3 == 0)) for k, t in enumerate(texts)]
    peak, net = _peak(lambda: toxicity.train(fitted, turns=1, epochs=1))
    assert net is not None
    assert peak < 11 * sum(map(len, texts))
