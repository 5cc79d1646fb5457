"""Each operator against a brute-force version, and its defined cases: nulls, empty and long texts, ties, repeated rows, empty tables, clashing columns."""

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

pytest.importorskip("vecgraph.llm")

import brute  # noqa: E402
import xxhash  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402

from vecgraph.llm import bpe, decontaminate, fmindex, langid, linededup, queries, secrets, simhash, suffixarray, topk, urlfilter, windows  # noqa: E402
from vecgraph.llm.common import small  # noqa: E402

VOCAB = queries.VOCABULARY
DOCS = "doc_id long, text string, lang string, source string, n_chars long, id long, h long, key string, hit long"
WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa".split()


def _texts(seed: int = 1, n: int = 60) -> list[str | None]:
    r = random.Random(seed)
    texts: list[str | None] = [" ".join(r.choice(WORDS) for _ in range(r.randrange(0, 120))) for _ in range(n)]
    long = " ".join(r.choice(WORDS) + str(r.randrange(300)) for _ in range(6000))
    passage = " ".join(r.choice(WORDS) + str(r.randrange(90)) for _ in range(80))
    texts += [None, "", " ", "\n\t", long, long, long[:9000] + " tail", passage, "x " + passage + " y", passage + "\n" + passage, "ÉÉ ß Σ \u0130 \u2003 end", "a" * 900, "b" * 900 + "a" * 500, "ab" * 600]
    return texts


def _frame(spark, texts, repeat=()):
    rows = [(i, t, ["en", "de", None][i % 3], f"src{i % 7}" if i % 11 else None, len(t or ""), 5, 6, "k", 7) for i, t in enumerate(texts)]
    rows += [rows[i] for i in repeat]
    return spark.createDataFrame(rows, DOCS).repartition(5), rows


def _by_id(df, *cols):
    return sorted((r.doc_id, *(r[c] for c in cols)) for r in df.collect())


# ---- op1 ----


def _judge(url, rules, default="allow"):
    m = re.match(r"(?s)^.*?://([^/?#]*)([^?#]*)", url or "")
    host, path = ("".join(c.lower() if "A" <= c <= "Z" else c for c in m[1]), m[2]) if m else ("", "")
    fits = [(len(h) + len(p), len(h), v == "block", h + p, v) for h, p, v in rules if (host == h or host.endswith("." + h) or h == "") and path.startswith(p)]
    best = max(fits, default=None)
    return host, path, best and best[3], best[4] if best else default


def test_url_filter(spark):
    r = random.Random(2)
    labels, tops = ["www", "a", "b", "EXAMPLE", "m"], ["com", "net", "org"]
    host = lambda: ".".join([r.choice(labels) for _ in range(r.randrange(0, 4))] + [r.choice(tops)])
    path = lambda: "".join(r.choice(["/", "/en", "/en/", "/es/x", "x", "?q=/en/", "#f"]) for _ in range(r.randrange(0, 4)))
    urls = [None, "", "no scheme", "http://", "http://?x", "x://y://z/en/"] + [f"http://{host()}{path()}" for _ in range(400)] + ["http://hot.example.com/en/1"] * 300
    rules = list({(h.lower(), p): (h.lower(), p, r.choice(["allow", "block"])) for h, p in [(host(), r.choice(["/", "/en/", "/en", "", "/es/x"])) for _ in range(60)]}.values()) + [("", "/en/", "block")]
    pages = spark.createDataFrame([(i, u, "k", "h") for i, u in enumerate(urls)], "page_id long, url string, key string, host string")
    got = {x.page_id: (x.host, x.path, x.rule, x.verdict) for x in urlfilter.url_filter(pages.repartition(4), spark.createDataFrame(rules, "host string, path string, verdict string")).collect()}
    assert got == {i: _judge(u, rules) for i, u in enumerate(urls)}
    twice = [("com", "/", "allow"), ("com", "/", "block")]
    one = urlfilter.url_filter(spark.createDataFrame([(1, "http://x.com/")] * 2, "page_id long, url string"), spark.createDataFrame(twice, "host string, path string, verdict string")).collect()
    assert [x.verdict for x in one] == ["block"] * 2
    assert urlfilter.url_filter(pages.limit(0), spark.createDataFrame(rules, "host string, path string, verdict string")).count() == 0
    assert {x.verdict for x in urlfilter.url_filter(pages, spark.createDataFrame([], "host string, path string, verdict string")).collect()} == {"allow"}


# ---- op2 ----


def _base(text):
    kinds = {"assign": (r"""((?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd])|(?:[Pp][Aa][Ss][Ss][Ww][Dd])|(?:[Ss][Ee][Cc][Rr][Ee][Tt])|(?:[Tt][Oo][Kk][Ee][Nn])|(?:[Aa][Pp][Ii]_?[Kk][Ee][Yy]))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6), "access": (r"AKIA[A-Z0-9]+", 0, 20), "hex": (r"[0-9a-f]+", 0, 24)}
    spans = [(m.start(), i, f"{k}:{m.start()}:{m.end()}") for i, (k, (p, g, n)) in enumerate(kinds.items()) for m in re.finditer(p, text) if len(m[g]) >= n]
    return [s for *_, s in sorted(spans)]


def test_secret_spans(spark):
    texts = _texts(3, 10) + ["token = \"" + "a1" * 20 + "\"", "API_KEY:abc", "api_key='abcdef'", "ſecret=abcdef toKen=abcdef", "AKIA" + "A" * 16, "AKIAshort", "secret=token=abcdefg", "é" * 5 + " password: hunter22", "password = " + "z" * 100_000, "f" * 24 + " " + "f" * 23]
    df, rows = _frame(spark, texts, repeat=(24, 25))
    for r in secrets.secret_digest(df).collect():
        want = _base(texts[r.doc_id] or "")
        assert r.base_sha256 == hashlib.sha256(",".join(want).encode()).hexdigest()
        assert (r.n_assign, r.n_access, r.n_hex) == tuple(sum(s.startswith(k) for s in want) for k in ("assign", "access", "hex"))
        assert set(want) <= set(filter(None, r.spans.split(",")))
    assert secrets.secret_digest(df).count() == len(rows) and secrets.secret_digest(df.limit(0)).count() == 0


def test_field_decodes_whole_texts_as_pieces():
    model = secrets.field()
    r = random.Random(4)
    for tokens, _, _ in secrets.generated(seed=99, lines=200):
        text = " ".join(tokens)
        whole = secrets.TOKEN.findall(text)
        file = sum(model.w[model.index["file", f]] for f in secrets.file_features(text) if ("file", f) in model.index)
        score = []
        for i, t in enumerate(whole):
            e = model.own(t) + file
            for place, j in (("prev", i - 1), ("prev2", i - 2), ("next", i + 1)):
                if 0 <= j < len(whole):
                    e = e + model.side(place, whole[j])
            score.append(e)
        path = model.viterbi(np.array(score), np.zeros(3), np.zeros(3))
        places = [m.span() for m in secrets.TOKEN.finditer(text)]
        want = []
        for i, y in enumerate(path):
            if y == secrets.B or (y == secrets.I and (i == 0 or path[i - 1] == secrets.O)):
                want.append(list(places[i]))
            elif y == secrets.I:
                want[-1][1] = places[i][1]
        assert model.spans(text) == [tuple(w) for w in want]
    del r


def test_field_finds_held_out_secrets():
    model = secrets.field()
    hit = true = found = 0
    for tokens, tags, _ in secrets.generated(seed=123, lines=400):
        text = " ".join(tokens)
        ends = np.cumsum([len(t) + 1 for t in tokens])
        want = {int(e - len(t) - 1) for t, e, y in zip(tokens, ends, tags, strict=True) if y == secrets.B}
        got = {s for s, _ in model.spans(text)}
        hit, true, found = hit + len(want & got), true + len(want), found + len(got)
    assert hit / true > 0.85 and hit / found > 0.9


# ---- op3 ----


def test_line_dedup_against_sql(spark, sf_dir, duck):
    from compare import same

    same(queries.QUERIES["op3_line_dedup"](spark, sf_dir), duck.sql(queries.ORACLES["op3_line_dedup"]))


@pytest.mark.parametrize("broadcast", [1_000_000, -1])
def test_line_dedup_cases(spark, monkeypatch, broadcast):
    monkeypatch.setattr(linededup, "BROADCAST", broadcast)
    boiler, rare = "All rights reserved by nobody.", "Seen on few sites, stays here."
    texts = [f"{boiler}\nown line number {i} of the text\n{rare if i < 12 else ''}" for i in range(60)] + [None, "", boiler, f"{boiler}\n {boiler} \nshort"]
    rows = [(i, t, f"site{i % 12 if i >= 12 else i % 3}") for i, t in enumerate(texts)]
    got = {r.doc_id: r for r in linededup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3), min_sites=10).collect()}
    assert got[0].text == texts[0] and got[60].text is None and got[61].text == "" and got[62].text == "" and got[63].text == "short"
    assert all(got[i].text == texts[i].split("\n", 1)[1] and got[i].n_cut == 1 for i in range(1, 60))
    assert linededup.dedup_lines(spark.createDataFrame([], "doc_id long, text string, source string")).count() == 0


@pytest.mark.parametrize("broadcast", [1_000_000, -1])
def test_line_dedup_judges_each_row_by_itself(spark, monkeypatch, broadcast):
    """Null ids, and one id over different texts: no row is cut where another one has boilerplate."""
    monkeypatch.setattr(linededup, "BROADCAST", broadcast)
    boiler = "All rights reserved by nobody."
    texts = [f"{boiler}\nclean line number {i} of this text" if i % 2 else f"clean line number {i} of this text\n{boiler}" for i in range(30)]
    ids = [i if i < 12 else None if i < 21 else 100 for i in range(30)]
    more = [(0, f"another text with the first id\n{boiler}\n{boiler}", "s0"), (None, None, "s1"), (100, None, "s1"), (None, texts[12], "s0"), (100, "no boilerplate here\nnor in this line", "s2")]
    rows = [(d, t, f"s{i % 12}") for i, (d, t) in enumerate(zip(ids, texts, strict=True))] + more

    def expected(doc, text):
        kept = [x for i, x in enumerate(text.split("\n")) if x != boiler or doc == 0 and boiler not in text.split("\n")[:i]] if text is not None else []
        n = text.count("\n") + 1 if text is not None else 0
        return str((doc, "\n".join(kept) if text is not None else None, n, n - len(kept)))

    got = linededup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3), min_sites=10)
    assert sorted(str((r.doc_id, r.text, r.n_lines, r.n_cut)) for r in got.collect()) == sorted(expected(d, t) for d, t, _ in rows)


# ---- oracles ----


@pytest.mark.parametrize("name", ["op7_decontamination", "op9_suffix_array", "op10_fm_index", "secret_base_counts"])
def test_against_sql(spark, sf_dir, duck, name):
    from compare import same

    same(queries.QUERIES[name](spark, sf_dir), duck.sql(queries.ORACLES[name]))


# ---- op4 ----


def test_language_id(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    got = queries.QUERIES["op4_language_id"](spark, sf_dir).join(docs.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in got if r.held_out]
    assert sum(r.lang_pred == r.lang for r in held) / len(held) > 0.95 and all(0 <= r.score <= 1 for r in got)


def test_language_id_cases(spark):
    rows = [(1, "the cat and the dog", "en"), (2, "der hund und die katze", "de"), (3, None, "en"), (4, "123 !!", "de"), (5, "und the", None), (6, "", "en")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumn("score", F.lit(9))
    model = langid.fit(df)
    assert sorted(model) == ["de", "en"]
    got = {r.doc_id: (r.lang_pred, r.score) for r in langid.predict(df, model).collect()}
    assert got[1][0] == "en" and got[2][0] == "de" and got[3] == got[4] == got[6] == ("und", 0.0)
    assert {r.lang_pred for r in langid.predict(df, langid.fit(df.limit(0))).collect()} == {"und"}
    assert langid.predict(df.limit(0), model).count() == 0


def test_language_id_against_brute_force(spark, sf_dir):
    rows = [(r.doc_id, r.text, r.lang) for r in spark.read.parquet(f"{sf_dir}/documents.parquet").orderBy("doc_id").limit(40).collect()]
    rows += [(1000, "Ünïcode ß text\n\nwith  gaps-and 3 numbers", "de"), (1001, None, "en"), (1002, "...", "en"), (1003, "x", None), (1003, "x", None), (1004, "long words " * 4000, "en")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3)
    train = [(lang, text) for i, text, lang in rows if i % 3]
    model = langid.fit(df.where("doc_id % 3 <> 0"))
    got = sorted((r.doc_id, r.lang_pred, r.score) for r in langid.predict(df, model).collect())
    want = sorted((r[0], lang, min(1.0, max(0.0, cos))) for r, (lang, cos) in zip(rows, brute.languages(train, [r[1] for r in rows], langid.DIMS), strict=True))
    assert [g[:2] for g in got] == [w[:2] for w in want] and np.allclose([g[2] for g in got], [w[2] for w in want], atol=1e-5)


def test_operators_keep_clashing_columns(spark):
    """Output names are a parameter: columns of the input with the usual names can stay."""
    names = ["cut_at", "cut_id", "cut_row", "n_lines", "n_cut", "lang_pred", "score", "row", "h", "first"]
    rows = [(i, f"All rights reserved by nobody.\nline {i} of this text", f"s{i}", *range(len(names))) for i in range(12)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, " + ", ".join(f"{n} long" for n in names))
    for most in (1_000_000, -1):
        old, linededup.BROADCAST = linededup.BROADCAST, most
        try:
            cut = linededup.dedup_lines(df, out=("made", "gone")).collect()
        finally:
            linededup.BROADCAST = old
        assert all([r[n] for n in names] == list(range(len(names))) for r in cut) and sum(r.gone for r in cut) == 11
    told = langid.predict(df, langid.fit(df.withColumn("lang", F.lit("en"))), out=("language", "cosine")).collect()
    assert all([r[n] for n in names] == list(range(len(names))) and r.language == "en" for r in told)
    assert linededup.dedup_lines(df).columns == [c for c in df.columns if c not in ("n_lines", "n_cut")] + ["n_lines", "n_cut"]


def test_one_of_each(spark):
    """Repeated rows, equal ids over different texts and rows without ids: one row of each group stays."""
    text = "some words that stand in this text more than once or twice"
    rows = [(7, text, "a"), (3, text, "b"), (3, text, "b"), (3, text, "c"), (None, text, "d"), (None, "another text without any id at all here", "e"), (None, "another text without any id at all here", "e"), (3, "third text that differs from all the other ones", "f"), (9, None, "g"), (8, "", "h")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, all string").withColumn("row", F.lit(1)).withColumn("m", F.create_map(F.lit("k"), F.lit("v")))
    got = simhash.one_of_each(docs.repartition(4))
    assert got.columns == docs.columns
    assert sorted((str(r.doc_id), r.text) for r in got.collect()) == sorted([("3", text), ("None", rows[5][1]), ("3", rows[7][1]), ("8", "")])
    assert simhash.one_of_each(docs.limit(0)).count() == 0


def test_binding_is_by_place():
    s = langid.Space(256)
    grams = [(a << 42) | (b << 21) | c for a, b, c in ((97, 98, 99), (99, 98, 97))]
    a, b = s.bind(grams[0]), s.bind(grams[1])
    assert abs(int(a.astype(int) @ b)) < 80 and set(np.unique(a)) == {-1, 1}


# ---- op5 ----


def test_topk_against_sql(spark, sf_dir, duck):
    from compare import same

    same(queries.QUERIES["op5_exact_topk"](spark, sf_dir), duck.sql(queries.ORACLES["op5_exact_topk"]))


def test_topk_cases(spark):
    r = np.random.default_rng(3)
    vec = [r.normal(size=6).tolist() for _ in range(300)]
    rows = [(i, v) for i, v in enumerate(vec)] + [(400, None), (401, [float("nan")] * 6), (402, [None] * 6), (403, [1.0] * 5), (404, []), (405, [float("inf")] * 6), (406, vec[1]), (7, vec[7]), (450, [0.0] * 6)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("id", F.lit(1)).withColumn("cell", F.lit(1))
    v = topk.integer_vectors(df)
    got = [tuple(x) for x in topk.exact_topk(v, v.where("vec_id % 50 = 0"), 5).orderBy("query_id", "rank").collect()]
    ints = [(i, np.floor(256 * np.array(x, np.float32).astype(float)).astype(int)) for i, x in rows if x and all(y is not None and np.isfinite(y) for y in x)]
    want = []
    for q, x in sorted(ints, key=lambda p: p[0]):
        if q % 50 == 0:
            best = sorted((-int(x @ y), i) for i, y in ints if i != q and len(y) == len(x))[:5]
            want += [(q, k + 1, i, -s) for k, (s, i) in enumerate(best)]
    assert got == want
    assert topk.exact_topk(v.limit(0), v.limit(0), 5).count() == 0


def test_segment_bounds_hold():
    r = np.random.default_rng(1)
    q, x = r.normal(size=(20, 64)), r.normal(size=(50, 64))
    true = q @ x.T
    coarse, fine = (topk.segment_features(q, s) @ topk.segment_features(x, s).T for s in (4, 16))
    assert (coarse >= true - 1e-9).all() and (fine >= true - 1e-9).all() and fine.mean() < coarse.mean()


# ---- op6 ----


def _prints(texts, shingle=4):
    out = []
    for t in texts:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        s = [" ".join(w[i : i + shingle]) for i in range(len(w) - shingle + 1)] or ([" ".join(w)] if w else [])
        hs = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
        out.append(sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs)))
    return out


def _components(ids, prints, distance=4):
    up = {i: i for i in ids}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, i in enumerate(ids):
        for b in range(a):
            if (prints[a] ^ prints[b]).bit_count() <= distance:
                x, y = root(i), root(ids[b])
                up[max(x, y)] = min(x, y)
    return {i: root(i) for i in ids}


def test_simhash(spark):
    texts = _texts(5, 40)
    base = "one two three four five six seven eight nine ten " * 20
    texts += [base + f"tail {i}" for i in range(30)] + ["ZERO", "zero"]
    df, rows = _frame(spark, texts, repeat=(3, 45))
    prints = _prints(texts)
    want = _components(list(range(len(texts))), prints)
    got = simhash.near_duplicates(df).collect()
    assert len(got) == len(rows) and all(r.fingerprint == f"{prints[r.doc_id]:016x}" and r.component_id == want[r.doc_id] for r in got)
    assert simhash.near_duplicates(df.limit(0)).count() == 0


def test_gray_index_with_small_groups(monkeypatch):
    monkeypatch.setattr(simhash, "FRONT", 50)
    r = np.random.default_rng(0)
    for _ in range(20):
        base = r.integers(0, 2**63, 6, dtype=np.uint64)
        fp = base[r.integers(0, 6, 250)]
        for _ in range(int(r.integers(0, 14))):
            fp = fp ^ (np.uint64(1) << r.integers(0, 64, 250, dtype=np.uint64))
        fp = np.unique(fp)
        cell = np.sort(r.integers(0, 3, len(fp)))
        star = simhash.GrayIndex(cell, fp, 4).stars().tolist()
        want = {}
        for c in range(3):
            here = np.flatnonzero(cell == c).tolist()
            want |= _components(here, [int(fp[i]) for i in here])
        pairs = {}
        assert all(pairs.setdefault(s, want[i]) == want[i] for i, s in enumerate(star)) and len(pairs) == len(set(want.values()))


def test_every_near_pair_meets_in_a_cell():
    for distance in (3, 4):
        for blocks in (distance + 1, distance + 2, distance + 3):
            ms = simhash.masks(blocks, distance)
            r = random.Random(blocks)
            for _ in range(200):
                x = r.getrandbits(64)
                y = x
                for b in r.sample(range(64), distance):
                    y ^= 1 << b
                assert any(x & m == y & m for m in ms)


def test_connected_components(spark):
    chain = [(i + 1, i) for i in range(40)] + [(100 + i, 100) for i in range(1, 30)] + [(7, 7)]
    got = {r.node: r.root for r in simhash.connected(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, **{i: 100 for i in range(100, 130)}}
    assert simhash.connected(spark.createDataFrame([], "a long, b long")).count() == 0


# ---- op7 ----


@pytest.mark.parametrize("block", [decontaminate.BLOCK_TERMS, 40])
def test_decontamination(spark, monkeypatch, block):
    monkeypatch.setattr(decontaminate, "BLOCK_TERMS", block)
    monkeypatch.setattr(decontaminate, "SEGMENT_BYTES", 2000)
    r = random.Random(6)
    texts = _texts(6, 40)
    items = [("7", "one TWO three"), ("8", ""), ("9", None), ("10", "alpha")] + [(str(20 + i), " ".join(r.choice(WORDS) for _ in range(r.randrange(5, 25)))) for i in range(12)]
    items += [("50", items[6][1]), (None, "alpha beta")]
    texts += [f"x {items[i][1]} y. {items[i][1]}" for i in range(4, 12)] + ["one, two; THREE", " ".join((items[9][1] or "").split()[:9])]
    df, rows = _frame(spark, texts, repeat=(50,))
    got = _by_id(decontaminate.contamination_digest(df, spark.createDataFrame(items, "item_id string, text string")), "n_words", "n_hit", "n_items", "items_sha256", "contaminated")
    found = brute.contamination(texts, items)
    want = sorted((row[0], n, h, len(i), brute.ids_digest(i), h > 0) for row in rows for n, h, i in [found[row[0]]])
    assert got == want
    assert decontaminate.contamination_digest(df.limit(0), spark.createDataFrame(items, "item_id string, text string")).count() == 0
    assert not any(r.contaminated for r in decontaminate.contamination_digest(df, spark.createDataFrame([], "item_id string, text string")).collect())


def test_long_texts_are_numbered_in_blocks(monkeypatch):
    text = " ".join(WORDS * 50).encode()
    whole = decontaminate.segment([text, None, b"alpha x"])
    monkeypatch.setattr(decontaminate, "SPLIT_BYTES", 7)
    for a, b in zip(whole, decontaminate.segment([text, None, b"alpha x"]), strict=True):
        assert list(a) == list(b)


def test_index_serves_several_test_sets(spark):
    docs = spark.createDataFrame([(None, "alpha beta gamma"), (1, "gamma beta alpha"), (1, "gamma beta alpha")], "doc_id long, text string")
    index = decontaminate.build_index(docs)
    for phrase, n in (("alpha beta", 1), ("beta alpha", 1), ("alpha", 2), ("beta gamma delta", 0)):
        items = spark.createDataFrame([(1, phrase)], "item_id long, text string")
        assert decontaminate.matches(index, items).count() == n


def test_near_matches(spark):
    items = spark.createDataFrame([(1, "zebra quagga okapi"), (2, "zebra unicorn")], "item_id long, text string")
    docs = spark.createDataFrame([(1, "okapi then a quagga near one zebra"), (2, "zebra " + "word " * 50 + "quagga okapi"), (3, "zebra")], "doc_id long, text string")
    got = {r.doc_id: r.near for r in decontaminate.contamination(docs, items, slop=8).collect()}
    assert got == {1: ["1"], 2: [], 3: []}


# ---- op8 ----


def test_bpe_equals_the_library(spark):
    tokenizers = pytest.importorskip("tokenizers")
    t = tokenizers.Tokenizer.from_file(VOCAB)
    r = random.Random(1)
    pool = [chr(c) for c in [*range(1, 700), 0x3A3, 0x130, 0x85, 0xA0, 0x2028, 0x301, 0x1100, 0x1161, 0xAC00, 0x4E2D, 0x1F600, 0xFB01, 0x660, 0x200B, 0xFEFF, 0x2126]] + ["<|endoftext|>", " <|startoftext|>", "'S", "'re", "  \n"]
    texts = _texts(7, 30) + ["".join(r.choice(pool) for _ in range(r.randrange(60))) for _ in range(400)] + ["ab" * 3000, "".join(r.choice("abcdefgh") for _ in range(4000))]
    df, rows = _frame(spark, texts, repeat=(4,))
    want = []
    for row in rows:
        ids = t.encode(row[1] or "", add_special_tokens=False).ids
        want.append((row[0], len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(t.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    assert _by_id(bpe.encode_digest(df, VOCAB), "n_tokens", "ids_sha256", "decoded_sha256") == sorted(want)
    full = {x.doc_id: x for x in bpe.encode(df, VOCAB).collect()}
    v = bpe.vocabulary(bpe.content_of(VOCAB))
    assert all(v.decode(x.ids) == x.decoded for x in full.values())
    assert bpe.encode_digest(df.limit(0), VOCAB).count() == 0


def test_short_and_long_merges_agree():
    v, r = bpe.vocabulary(bpe.content_of(VOCAB)), random.Random(3)
    for _ in range(300):
        parts = v.parts("".join(r.choice("abcdeinrst") for _ in range(r.randrange(1, 40))))
        assert v.merge(list(parts)) == v.merge_long(list(parts))


# ---- op9, op10 ----


def _kept(split, texts, window):
    units = [split((t or "").encode()) for t in texts]
    seen = Counter(tuple(u[i : i + window]) for u in units for i in range(len(u) - window + 1))
    out = []
    for u in units:
        gone = np.zeros(len(u), bool)
        for i in range(len(u) - window + 1):
            if seen[tuple(u[i : i + window])] > 1:
                gone[i : i + window] = True
        runs = int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum())
        out.append((len(u), int(gone.sum()), runs, [x for x, g in zip(u, gone, strict=True) if not g]))
    return out


@pytest.mark.parametrize("window,gram,hot", [(400, 256, 512), (30, 8, 512), (7, 7, 512), (400, 256, 1), (30, 8, 2), (12, 5, 1)])
def test_suffix_array_dedup(spark, monkeypatch, window, gram, hot):
    monkeypatch.setattr(windows, "HOT", hot)
    monkeypatch.setattr(suffixarray, "GRAM", gram)
    monkeypatch.setattr(windows, "CHUNK", 20_000)
    monkeypatch.setattr(windows, "TOGETHER", 3000)
    texts = _texts(8, 40)
    df, rows = _frame(spark, texts, repeat=(2, 30))
    want = sorted((r[0], n, g, k, hashlib.sha256(bytes(kept)).hexdigest()) for r, (n, g, k, kept) in zip(rows, _kept(lambda b: b, [r[1] for r in rows], window), strict=True))
    assert _by_id(suffixarray.kept_digest(df, window), "n_bytes", "n_removed", "n_spans", "kept_sha256") == want
    assert suffixarray.kept_digest(df.limit(0), window).count() == 0


@pytest.mark.parametrize("window,gram,hot", [(35, 15, 512), (5, 2, 512), (3, 3, 512), (35, 15, 1), (5, 2, 1)])
def test_fm_index_dedup(spark, monkeypatch, window, gram, hot):
    monkeypatch.setattr(windows, "HOT", hot)
    monkeypatch.setattr(fmindex, "GRAM", gram)
    monkeypatch.setattr(windows, "CHUNK", 20_000)
    monkeypatch.setattr(windows, "TOGETHER", 500)
    texts = _texts(9, 40)
    df, rows = _frame(spark, texts, repeat=(2, 30))
    want = sorted((r[0], n, g, hashlib.sha256(b" ".join(kept)).hexdigest()) for r, (n, g, _, kept) in zip(rows, _kept(bytes.split, [r[1] for r in rows], window), strict=True))
    assert _by_id(fmindex.kept_digest(df, window), "n_words", "n_removed", "kept_sha256") == want
    assert fmindex.kept_digest(df.limit(0), window).count() == 0


@pytest.mark.parametrize("hot", [512, 1])
def test_clashing_hashes_decide_nothing(spark, monkeypatch, hot):
    """Half of every content digest is one value, as if all pieces' hashes clashed: the engines see the texts."""

    class Clash(windows.Units):
        def digests(self, *args):
            c, e = super().digests(*args)
            return np.zeros_like(c), e

    monkeypatch.setattr(windows, "Units", Clash)
    monkeypatch.setattr(windows, "HOT", hot)
    monkeypatch.setattr(suffixarray, "GRAM", 8)
    monkeypatch.setattr(fmindex, "GRAM", 2)
    df, rows = _frame(spark, _texts(10, 25), repeat=(1, 27))
    for kept, window, split, name in ((suffixarray.kept_digest, 30, lambda b: b, "n_bytes"), (fmindex.kept_digest, 5, bytes.split, "n_words")):
        want = sorted((r[0], n, g) for r, (n, g, _, _) in zip(rows, _kept(split, [r[1] for r in rows], window), strict=True))
        assert _by_id(kept(df, window), name, "n_removed") == want


@pytest.mark.parametrize("kind", ["bytes", "words"])
def test_slices_hold_each_window_once(kind):
    r = random.Random(3)
    text = " ".join("x" * r.randrange(1, 9) + "\n" * r.randrange(3) for _ in range(400)).encode()
    whole = windows.Units(kind).split(text)
    got = [(lo + i, tuple(part[i : i + 7])) for lo, part in windows.Units(kind, 20).slices(text, 7) for i in range(len(part) - 6)]
    assert got == [(i, tuple(whole[i : i + 7])) for i in range(len(whole) - 6)]
    assert [list(p) for _, p in windows.Units(kind, 20).slices(b"", 7)] in ([], [[]])


def test_long_texts_are_read_as_short_ones(monkeypatch):
    r = random.Random(4)
    text = b"\x0b " + b" \n".join(b"w%d" % r.randrange(99) for _ in range(500)) + b"\t"
    short, n = windows.Units("words").reader(text), len(text.split())
    want = [short(a, z) for a in range(0, n, 37) for z in (a, a + 1, n)]
    kept = fmindex.kept_words(text, [[0, 3], [7, 400]])
    monkeypatch.setattr(windows, "LONG", 0)
    monkeypatch.setattr(fmindex, "LONG", 11)
    long = windows.Units("words").reader(text)
    assert [long(a, z) for a in range(0, n, 37) for z in (a, a + 1, n)] == want
    assert fmindex.kept_words(text, [[0, 3], [7, 400]]) == kept == (n, 396, hashlib.sha256(b" ".join(text.split()[3:7] + text.split()[400:])).hexdigest())


def test_long_runs_of_one_key_are_cut(monkeypatch):
    """A text of one byte is a single run; no piece may be as long as the text."""
    data = np.zeros(50_000, np.uint64)
    _, s, n, m, again = windows.pieces(data, np.array([50_000]), 400, 256)
    assert n.max() == windows.PIECE and n.sum() == 50_000 - 399 and len(set(m.tolist())) == 1 and again.all()


def test_matching_statistics():
    r = random.Random(2)
    seq = np.array([r.randrange(1, 4) for _ in range(300)] + [0])
    index = fmindex.FMIndex(seq, 40)
    got = index.matching(np.arange(300), 20)
    assert (fmindex.FMIndex(seq, 40, 1).matching(np.arange(300), 20) == got).all() and len(index.seeds) > 3  # wherever searches begin
    for e in range(300):
        n = 0
        while n < 20 and n <= e and sum(seq[i : i + n + 1].tolist() == seq[e - n : e + 1].tolist() for i in range(300 - n)) > 1:
            n += 1
        assert got[e] == n


def test_wavelet_ranks():
    r = np.random.default_rng(4)
    seq = r.integers(0, 37, 500)
    tree = fmindex.Wavelet(seq, 36)
    x, i = r.integers(0, 37, 200), r.integers(0, 501, 200)
    assert (tree.rank(x, i) == [(seq[:b] == a).sum() for a, b in zip(x, i, strict=True)]).all()


def test_suffixes_are_ordered():
    r = random.Random(5)
    for _ in range(60):
        texts = ["".join(r.choice("abc") for _ in range(r.randrange(1, 30))).encode() for _ in range(4)]
        data, end = b"".join(texts), np.cumsum([len(t) for t in texts])
        order = suffixarray.suffix_order(data, end, np.ones(len(data), bool), 50)
        ends = end[np.searchsorted(end, order, "right")]
        keys = [data[i:e] for i, e in zip(order, ends, strict=True)]
        assert sorted(order.tolist()) == list(range(len(data))) and keys == sorted(keys)


def test_index_segments_lie_in_row_groups_of_bounded_size(spark, monkeypatch):
    """Writers and readers hold a row group: one of the index has few segments, however many its task has made."""
    import pyarrow.dataset as ds

    monkeypatch.setattr(decontaminate, "SEGMENT_BYTES", 200_000)
    texts = [" ".join(f"w{(i * 7919 + j * 31) % 9973}" for j in range(4000)) for i in range(400)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1)
    index = decontaminate.build_index(df)
    groups = [g for f in ds.dataset([p.removeprefix("file://") for p in index.inputFiles()]).get_fragments() for g in f.row_groups]
    assert sum(g.num_rows for g in groups) == index.count() > 20
    assert max(g.num_rows for g in groups) <= 3


def test_workers_keep_one_operators_tables():
    """A worker that goes on with another operator no longer holds the last one's tables (the pipeline's stages share workers)."""
    import gc
    import weakref

    batch = pa.RecordBatch.from_pydict({"text": ["a b", None]})
    space, vocab = weakref.ref(langid.space()), None
    assert langid.space() is space()
    assert [b.num_rows for b in small(iter([batch]), operator="langid")] == [2] and space() is not None
    vocab = weakref.ref(bpe.vocabulary(bpe.content_of(VOCAB)))
    gc.collect()
    assert space() is None and vocab() is not None
    assert [b.num_rows for b in small(iter([batch]))] == [2]
    gc.collect()
    assert vocab() is None
