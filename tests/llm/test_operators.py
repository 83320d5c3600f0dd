"""Training-data operators against brute force, exact round trips and held-out accuracy, with edge cases."""

import hashlib
import re
import zlib

import numpy as np
import public_tokenizers as P
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer, models, normalizers

from ctxviews.llm import bpe_codec, cap_neardup, chroma, common, jaccard_join, language_id, packing, quality, suffix_array, suffix_dedup, token_counts, url_filter

DATA = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score double, t string, k1 long"


def frame(spark, texts, **more):
    return spark.createDataFrame([(i, t, more.get("lang", "en"), "s" if i % 3 else None, len(t or ""), 0.5, "x", 1) for i, t in enumerate(texts)], SCHEMA)


EDGE = [None, "", " \t\n", "a", "a b c d", "Ünï 你好 🎉 ΣΑΣ", "<|endoftext|> x <unk> <0x0A>", "na " * 3000, "It's I'LL 2023!!", "same text here", "same text here", "\x1c\x85 z"]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet")


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})))


# --- 1 ---------------------------------------------------------------------------------------


def test_suffix_array():
    rng = np.random.default_rng(2)
    for _ in range(400):
        t = np.append(rng.integers(1, 4, rng.integers(1, 40)), 0)
        assert suffix_array.suffix_array(t).tolist() == sorted(range(len(t)), key=lambda i: t[i:].tolist())


def brute_removed(texts, length):
    raw = [(t or "").encode() for t in texts]
    seen: dict[bytes, int] = {}
    for b in raw:
        for i in range(len(b) - length + 1):
            seen[b[i : i + length]] = seen.get(b[i : i + length], 0) + 1
    out = []
    for b in raw:
        cover = np.zeros(len(b), bool)
        for i in range(len(b) - length + 1):
            if seen[b[i : i + length]] > 1:
                cover[i : i + length] = True
        kept = np.frombuffer(b, np.uint8)[~cover].tobytes()
        out.append((len(b), int(cover.sum()), int((np.diff(np.concatenate([[0], cover.astype(int)])) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    return out


def planted(seed=0):
    rng = np.random.default_rng(seed)
    word = lambda: "".join(rng.choice(list("abcdeé"), rng.integers(2, 6)))
    passage = " ".join(word() for _ in range(40))
    texts = list(EDGE)
    for i in range(24):
        body = [word() for _ in range(30)]
        if i % 3 == 0:
            body.insert(int(rng.integers(0, 30)), passage)
        texts.append(" ".join(body))
    near = [word() for _ in range(80)]
    for i in range(6):
        v = list(near)
        v[int(rng.integers(0, 80))] = word()
        texts.append(" ".join(v))
    return [*texts, texts[-1], texts[-2] + texts[-2], "ab" * 300]


@pytest.mark.parametrize("hot", [10_000, 3])
def test_suffix_dedup_brute_force(spark, monkeypatch, hot):
    monkeypatch.setattr(suffix_dedup, "HOT_SLOTS", hot)
    texts = planted()
    got = suffix_dedup.dedup(frame(spark, texts), spark, ["doc_id"], 60).orderBy("doc_id").collect()
    assert [tuple(r)[1:] for r in got] == brute_removed(texts, 60)


def test_suffix_dedup_text_and_empty_table(spark):
    d = frame(spark, ["é" * 200, "x" + "é" * 150, None])
    r = suffix_dedup.dedup(d, spark, ["doc_id"], 100, with_text=True).orderBy("doc_id").collect()
    assert [x.kept_text for x in r] == ["", "x", None]
    assert suffix_dedup.dedup(d.limit(0), spark, ["doc_id", "k1"], 100).count() == 0


# --- 2, 6 --------------------------------------------------------------------------------------


def test_token_counts_equal_the_library(spark, docs):
    pieces = token_counts.read_pieces(P.path("piece_bpe_32k.model"))
    tk = Tokenizer(models.Unigram(pieces, unk_id=0, byte_fallback=True))
    tk.normalizer = normalizers.Sequence([normalizers.Prepend("▁"), normalizers.Replace(" ", "▁")])
    texts = EDGE + [r.text for r in docs.collect()]
    got = token_counts.count_tokens(frame(spark, texts), spark, P.path("piece_bpe_32k.model")).orderBy("doc_id").collect()
    assert [r.n_tokens for r in got] == [len(tk.encode(t or "", add_special_tokens=False).ids) for t in texts]


def test_whole_text_counter_agrees():
    """Vocabularies that cannot be cut into words take whole texts."""
    pieces = [("<unk>", 0.0), ("a", -1.5), ("b", -1.25), ("ab", -2.6), ("b▁a", -2.0), ("▁", -1.0)]
    c = token_counts.UnigramCounter(pieces)
    assert c.cut is None
    tk = Tokenizer(models.Unigram(pieces, unk_id=0))
    tk.normalizer = normalizers.Sequence([normalizers.Prepend("▁"), normalizers.Replace(" ", "▁")])
    rng = np.random.default_rng(1)
    for _ in range(200):
        t = "".join(rng.choice(list("ab zq"), 12))
        assert c.text(t) == len(tk.encode(t, add_special_tokens=False).ids)


def test_bpe_codec_equals_the_library(spark, docs):
    tk = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    texts = EDGE + ["hehehehehe hehe aaaaaaa banana ananananan"] + [r.text for r in docs.collect()]
    got = bpe_codec.encode(frame(spark, texts), spark, P.path("word_bpe_49k.json"), with_text=True).orderBy("doc_id").collect()
    for r, t in zip(got, texts, strict=True):
        ids = tk.encode(t or "", add_special_tokens=False).ids
        assert r.ids == " ".join(map(str, ids)) and r.n_tokens == len(ids)
        assert r.decoded == tk.decode(ids, skip_special_tokens=False)
        assert r.ids_sha256 == hashlib.sha256(r.ids.encode()).hexdigest()


# --- 3 -----------------------------------------------------------------------------------------


def test_url_rules_brute_force(spark):
    pages = spark.read.parquet(f"{DATA}/pages.parquet").select("page_id", "url")
    odd = [(10_000 + i, u) for i, u in enumerate([None, "", "no scheme", "http://", "HTTP://COM/en/", "x://Example.NET/de/8?q", "x://notcom/en/", "a://b.org/es/#f", "http://example.com/en/7/x", "http://h?x://y/z", "http://com\n/en/"])]
    pages = pages.unionByName(spark.createDataFrame(odd, "page_id long, url string")).withColumn("host", F.lit("clash"))
    got = {r.page_id: r for r in url_filter.judge(pages, spark).collect()}
    for r in pages.collect():
        u = r.url or ""
        rest = u[u.index("://") + 3 :] if "://" in u else ""
        host = re.match(r"[^/?#]*", rest)[0]
        path = re.match(r"[^?#]*", rest[len(host) :])[0]
        host = "".join(c.lower() if "A" <= c <= "Z" else c for c in host)
        fit = [(len(rule), v, rule) for v, rule in url_filter.RULES for h, _, p in [rule.partition("/")] if (host == h or host.endswith("." + h)) and path.startswith("/" + p)]
        g = got[r.page_id]
        assert (g.host, g.path, g.rule) == (host, path, max(fit)[2] if fit else None)
        assert g.verdict == max(fit)[1] if fit else g.verdict in ("block", "allow")


def test_boosting_learns_and_handles_one_class(spark):
    rng = np.random.default_rng(0)
    x = rng.random((2000, 5))
    y = ((x[:, 0] > 0.5) ^ (x[:, 1] > 0.5)).astype(float)
    assert ((url_filter.Boosted.fit(x[:1500], y[:1500]).margin(x[1500:]) > 0) == y[1500:]).mean() > 0.95
    one = spark.createDataFrame([(1, "http://a.com/en/1"), (2, "http://b.xx/q")], "page_id long, url string")
    assert {r.verdict for r in url_filter.judge(one, spark).collect()} == {"block"}
    assert url_filter.judge(one.limit(0), spark).count() == 0


# --- 4 -----------------------------------------------------------------------------------------


def brute_components(texts):
    sets = []
    for t in texts:
        w = words(t)
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    up = list(range(len(texts)))

    def root(v):
        while up[v] != v:
            v = up[v]
        return v

    for i in range(len(sets)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                a, b = root(i), root(j)
                up[max(a, b)] = min(a, b)
    return [(len(s), root(i)) for i, s in enumerate(sets)]


@pytest.mark.parametrize("group", [64, 2])
def test_jaccard_join_brute_force(spark, monkeypatch, group):
    monkeypatch.setattr(jaccard_join, "HOT_GROUP", group)
    rng = np.random.default_rng(4)
    texts = planted(5)
    base = [f"w{k}" for k in rng.integers(0, 60, 70)]
    for i in range(40):  # a chain of drifting copies: neighbours link, ends do not
        base = list(base)
        base[int(rng.integers(0, len(base)))] = f"v{i}"
        texts.append(" ".join(base))
    got = jaccard_join.join(frame(spark, texts), spark).orderBy("doc_id").collect()
    assert [(r.n_shingles, r.component_id) for r in got] == brute_components(texts)


def test_jaccard_join_on_tables(spark, docs):
    texts = [r.text for r in docs.orderBy("doc_id").collect()]
    ids = [r.doc_id for r in docs.orderBy("doc_id").collect()]
    got = jaccard_join.join(docs, spark).orderBy("doc_id").collect()
    assert [(r.n_shingles, r.component_id) for r in got] == [(n, ids[c]) for n, c in brute_components(texts)]


def test_jaccard_join_odd_tables(spark):
    assert jaccard_join.join(frame(spark, []).limit(0), spark).count() == 0
    twice = frame(spark, ["a b c d e f", "x", None]).union(frame(spark, ["a b c d e f", "x", None]))
    assert sorted((r.doc_id, r.component_id) for r in jaccard_join.join(twice, spark).collect()) == [(0, 0), (0, 0), (1, 1), (1, 1), (2, 2), (2, 2)]


def test_suffix_bound_is_a_lower_bound():
    rng = np.random.default_rng(8)
    for _ in range(300):
        a, b = (np.unique(rng.integers(0, 60, rng.integers(0, 40)).astype(np.uint64)) for _ in range(2))
        assert jaccard_join.suffix_bound(a, b) <= len(np.setxor1d(a, b))


def test_components_of_chains_and_stars(spark):
    rng = np.random.default_rng(1)
    e = [(i, i + 1) for i in range(200)] + [(1000, 1000 + k) for k in range(1, 50)] + [(int(a), int(b)) for a, b in rng.integers(2000, 2100, (60, 2))]
    up: dict[int, int] = {}

    def root(v):
        while up.setdefault(v, v) != v:
            v = up[v]
        return v

    for a, b in e:
        x, y = root(a), root(b)
        up[max(x, y)] = min(x, y)
    got = {r.node: r.component for r in common.components(spark.createDataFrame(e, "src long, dst long"), spark).collect()}
    assert got == {v: root(v) for v in list(up) if v in got} and set(got) >= {v for a, b in e if a != b for v in (a, b)}


# --- 5 -----------------------------------------------------------------------------------------


def test_cap_filters(spark, monkeypatch):
    monkeypatch.setattr(cap_neardup, "BLOCK", 40)  # groups in pairs of blocks too
    rng = np.random.default_rng(6)
    base = rng.normal(size=(60, 32))
    x = [b + rng.normal(size=32) * s * np.linalg.norm(b) / 32**0.5 for b in base for s in (0, 0.05, 0.2, 0.3)] + [base[0] + rng.normal(size=32) * 0.1 for _ in range(150)]
    v = [[float(np.float32(c)) for c in r] for r in x] + [None, [], [0.0] * 32, [1.0, None] + [0.0] * 30, [float("nan")] + [1.0] * 31, [float("inf")] + [1.0] * 31, [1.0, 2.0]]
    v += [v[0], v[0]]
    got = cap_neardup.near_duplicates(spark.createDataFrame([(i, r, 1) for i, r in enumerate(v)], "vec_id long, embedding array<float>, label int"), spark).orderBy("vec_id").collect()
    ok = [i for i, r in enumerate(v) if r and len(r) == 32 and all(c is not None and np.isfinite(c) for c in r) and any(r)]
    u = np.array([v[i] for i in ok])
    u /= np.linalg.norm(u, axis=1, keepdims=True)
    n = (u @ u.T >= 0.95).sum(1) - 1
    found = np.array([got[i].n_links for i in ok])
    assert (found <= n).all() and found.sum() >= 0.9 * n.sum()
    assert all(got[i].n_links == 0 and got[i].component_id == i and got[i].kept for i in range(len(v)) if i not in ok and i < len(v))
    assert got[len(v) - 1].component_id == got[0].component_id == 0
    assert cap_neardup.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>"), spark).count() == 0


# --- 7 -----------------------------------------------------------------------------------------


def check_packing(rows, texts):
    tk = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    by_doc: dict[int, list] = {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
    for i, t in enumerate(texts):
        ids = [*tk.encode(t or "", add_special_tokens=False).ids, 0]
        at = 0
        for r in sorted(by_doc[i], key=lambda r: r.start):
            assert (r.start, r.doc_tokens) == (at, len(ids)) and r.length > 0
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids)
    seqs: dict[int, list] = {}
    for r in rows:
        seqs.setdefault(r.sequence_id, []).append((r.offset, r.length))
    padding = 0
    for pieces in seqs.values():
        at = 0
        for o, n in sorted(pieces):
            assert o == at
            at += n
        assert at <= 1024
        padding += 0 if at & (at - 1) == 0 else 1024 - at
    assert padding == 0
    return seqs


def test_packing(spark, docs):
    texts = EDGE + [r.text for r in docs.collect()]
    check_packing(packing.pack(frame(spark, texts).repartition(3), spark, P.path("byte_bpe_50k.json")).collect(), texts)
    assert packing.pack(frame(spark, [""]).limit(0), spark, P.path("byte_bpe_50k.json")).count() == 0


def test_windows_keep_the_mixture():
    m = packing.Mixture([900_000, 90_000, 9_000, 1, 55_555], segment=100)
    for k in range(m.segments):
        at, take = m.segment(k)
        a, b = m.bounds(k)
        assert (take >= 0).all() and (at[0] == m.taken(m.start(a))).all()
        whole = take[: max(0, m.full - a)]
        assert (np.abs(whole - 1024 * m.n / m.total) <= 2.5).all() and (whole.sum(1) == 1024).all()


# --- 8, 9 --------------------------------------------------------------------------------------


def test_language_id(spark):
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").withColumn("held_out", F.crc32(F.col("doc_id").cast("string")) % 4 == 2)
    m = language_id.fit(d.filter("not held_out"), spark)
    r = language_id.identify(d, spark, m, ["doc_id", "held_out", "lang"])
    assert r.filter("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0] > 0.97
    assert r.filter("score < 0 or score > 1").count() == 0
    e = language_id.identify(frame(spark, [None, "", "12 !?", "The with and of the is"]), spark, m, ["doc_id", "score"][:1]).orderBy("doc_id").collect()
    assert [x.lang_pred for x in e] == ["und", "und", "und", "en"]
    none = language_id.fit(d.limit(0), spark)
    assert {x.lang_pred for x in language_id.identify(frame(spark, ["abc"]), spark, none, ["doc_id"]).collect()} == {"und"}
    one = language_id.fit(d.filter("lang = 'de'"), spark)
    assert {x.lang_pred for x in language_id.identify(frame(spark, ["abc", "1"]), spark, one, ["doc_id"]).collect()} == {"de", "und"}


def test_codewords_are_far_apart():
    for n in (2, 3, 4, 9, 30):
        c = language_id.codewords(n)
        d = [(c[i] != c[j]).sum() for i in range(n) for j in range(i)]
        assert min(d) >= 2


def test_quality(spark):
    base = "/root/testdata/sf0.1"
    d = spark.read.parquet(f"{base}/documents.parquet")
    lab = spark.read.parquet(f"{base}/labels.parquet").withColumn("held_out", F.crc32(F.col("doc_id").cast("string")) % 5 == 0)
    m = quality.fit(d, lab.filter("not held_out"), spark)
    s = quality.score(d, spark, m, ["doc_id"]).join(lab.filter("held_out"), "doc_id").select("score", "quality").collect()
    good = np.array([r.score for r in s if r.quality == 1])
    bad = np.array([r.score for r in s if r.quality == 0])
    assert (good >= 0.3).mean() > 0.97 and (bad < 0.3).mean() > 0.8
    assert all(0 <= r.score <= 1 for r in quality.score(frame(spark, EDGE), spark, m, ["doc_id"]).collect())
    none = quality.fit(d, lab.limit(0), spark)
    assert {r.score for r in quality.score(frame(spark, ["a", None]), spark, none, ["doc_id"]).collect()} == {0.5}


# --- 10 ----------------------------------------------------------------------------------------


def test_chroma_alignment(spark):
    rng = np.random.default_rng(9)
    v = rng.uniform(-0.25, 0.25, (12, 64))
    rows = [(i * 50, [float(x) for x in r]) for i, r in enumerate(v)]
    noisy = np.frombuffer(chroma.sonify(v[0]), "<i2").astype(float)
    fp = chroma.fingerprint(chroma.sonify(v[0]))
    late = chroma.fingerprint((noisy[2 * chroma.HOP * 5 :] + rng.normal(0, 200, len(noisy) - 2 * chroma.HOP * 5)).astype("<i2").tobytes())
    hit = list(chroma.QueryBlock([7], [fp]).align(late))
    assert len(hit) == 1 and hit[0][0] == 7 and hit[0][1] == 10
    assert not list(chroma.QueryBlock([7], [chroma.fingerprint(chroma.sonify(v[1]))]).align(fp))
    rows += [(5001, rows[0][1]), (5002, None), (5003, []), (5004, [float("nan")] * 64)]
    p = chroma.fingerprints(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), spark, "vec_id", "embedding", chroma.sonify)
    r = {x.vec_id: x for x in chroma.search(common.keep(p, spark), spark).collect()}
    assert len(r) == len(rows) and r[5001].class_id == 0 and r[5002].n_items == 0 and r[5002].class_id is None
    assert [m.class_id for m in r[0].matches] == [0] and r[0].matches[0].bit_errors == 0 and r[50].matches == []
    assert chroma.search(common.keep(p.limit(0), spark), spark).count() == 0


def test_fingerprint_of_short_audio():
    assert len(chroma.fingerprint(None)) == len(chroma.fingerprint(b"")) == len(chroma.fingerprint(b"\0" * 101)) == 0
    assert chroma.bit_errors(np.array([1], np.uint32), np.array([3], np.uint32), 0) == (1 / 32, 1)


def test_op1_returns_the_remaining_text_as_documents_name_it(spark):
    from ctxviews.llm.queries import QUERIES

    r = QUERIES["op1_suffix_dedup"](spark, "/root/testdata/sf0.001")
    assert r.columns == ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "text"]
    docs = {x.doc_id: x.text for x in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()}
    rows = r.collect()
    assert any(x.n_removed for x in rows) and all((x.text == docs[x.doc_id]) == (x.n_removed == 0) for x in rows)
