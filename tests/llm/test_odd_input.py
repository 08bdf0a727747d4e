"""Nulls, empty and long texts, ties, repeats, empty tables and further columns: the results that docstrings name."""

import brute
import pytest

LONG = "word%d " * 3
DOCS = [
    (1, None, "b"), (2, "", None), (3, "  \t\n ", "a"), (4, "Same Text here", "a"), (5, "same text HERE", None), (6, "same text HERE", "b"), (None, "same text here", "b"),
    (7, " ".join(f"w{i}" for i in range(40_000)), "a"), (8, "Ünï çödé ÀÉ \U0001f600 x@y.zz +1 (555) 123-4567 a b c", "b"), (8, "Ünï çödé ÀÉ \U0001f600 x@y.zz +1 (555) 123-4567 a b c", "b"), (9, "one", "a"), (10, "ONE", "a"),
]


@pytest.fixture(scope="module")
def docs(spark):
    df = spark.createDataFrame(DOCS, "doc_id long, text string, source string")
    return df.selectExpr("*", "'x' as id", "1 as n", "2 as size", "3 as h", "'y' as spans", "0 as row", "'z' as mark", "0.5 as score", "1 as digest", "array(1) as sources", "'q' as t", "1 as kept", "'m' as lang")


@pytest.fixture(scope="module")
def none(docs):
    return docs.where("1 = 0")


def test_pii(docs, none):
    from lossband.llm import pii

    got = pii.find(docs).collect()
    assert len(got) == len(DOCS) and pii.find(none).count() == 0
    spans = {r["doc_id"]: r["spans"] for r in got}
    assert spans[1] == [] and spans[2] == []
    assert [(s["start"], s["end"], s["kind"]) for s in spans[8]] == [(a, b, k) for a, _, b, k in brute.base_spans(DOCS[8][1])]
    masked = {r["doc_id"]: r["text"] for r in pii.mask(docs).collect()}
    assert masked[8] == "Ünï çödé ÀÉ \U0001f600 <email> <phone> a b c"


def test_pii_patterns(spark):
    from lossband.llm import pii

    texts = [
        "a@b.c_d@e.f..g@h.i", "1.2.3.4.5.6.7.8 999.1.1.1 01.002.0003.4", "4111 1111 1111 1111 and 4111-1111-1111-1112 4111111111111111", "+1--(2).3 4 5 6 7 8 9 0- +12", "x" * 5000 + "@", "1 " * 8000, "1." * 5000, "9" * 9000,
        "@@a@b", "IBAN DE89 3704 0044 0532 0130 00 end", "call 555-123-4567", "SSN 123-45-6789", "a@b.c@d.e", "+1 555 123 4567+1 555 123 4567",
    ]
    got = {r["doc_id"]: r["spans"] for r in pii.find(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    base = {k.name for k in pii.KINDS if k.base}
    for i, t in enumerate(texts):
        assert [(s["start"], s["end"], s["kind"]) for s in got[i] if s["kind"] in base] == [(a, b, k) for a, _, b, k in brute.base_spans(t)], t[:40]
    kinds = [s["kind"] for v in got.values() for s in v]
    assert {"iban", "national_id", "local_phone"} <= set(kinds)


def test_pii_numbers_with_dots(spark):
    """The cheap sign of a kind lets every match of its pattern through, hyphen or not."""
    from lossband.llm import pii

    texts = ["call 555.123.4567", "tel (555) 123.4567 now", "call 555 123-4567", "555.123.4567 alone"]
    got = {r["doc_id"]: r["spans"] for r in pii.find(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [[(s["start"], s["end"], s["kind"]) for s in got[i]] for i in range(4)] == [[(5, 17, "local_phone")], [(4, 18, "local_phone")], [(5, 17, "local_phone")], []]


def test_pii_kinds_beyond_the_base(spark):
    """IBANs, national numbers and local telephone numbers by definition: pattern, check, context within reach, no overlap of one kind."""
    import random
    import re

    from lossband.llm import pii

    def iban_ok(m):
        bare = m.replace(" ", "")
        return 15 <= len(bare) <= 34 and int("".join(str(int(c, 36)) for c in bare[4:] + bare[:4])) % 97 == 1

    checks = {"iban": iban_ok, "national_id": lambda m: not re.search("^(000|666|9)|-00-|-0000$", m), "local_phone": lambda m: len(re.sub("[^0-9]", "", m)) == 10}
    rng = random.Random(2)
    parts = ["DE89370400440532013000", "GB82 WEST 1234 5698 7654 32", "DE88370400440532013000", "123-45-6789", "000-12-3456", "987-65-4321", "555-123-4567", "(555) 123-4567", "555.123.4567", "SSN", "social security", "call", "tel", "account", "phone", "word", "x" * 50, ",", "\n", "9", "+1"]
    texts = [" ".join(rng.choice(parts) for _ in range(rng.randrange(1, 25))) for _ in range(300)]
    got = {r["doc_id"]: r["spans"] for r in pii.find(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    seen = set()
    for i, t in enumerate(texts):
        want = []
        for k, kind in enumerate(pii.KINDS):
            if kind.base or kind.name == "local_phone":
                continue
            for m in re.finditer(kind.pattern, t):
                if checks[kind.name](m[0]):
                    near = t[max(0, m.start() - pii.NEAR) : max(0, m.start() - pii.NEAR) + len(m[0]) + 2 * pii.NEAR].lower()
                    if kind.score + (kind.bonus if re.search(kind.context, near) else 0) >= pii.THRESHOLD:
                        want.append((m.start(), k, m.end(), kind.name))
                        seen.add(kind.name)
        assert [(s["start"], s["k"], s["end"], s["kind"]) for s in got[i] if s["kind"] in ("iban", "national_id")] == sorted(want), t
    assert seen == {"iban", "national_id"}


def test_pii_of_long_texts_is_linear(spark):
    import time

    from lossband.llm import pii

    def took(n):
        df = spark.createDataFrame([(1, "12 a " * n + "1.2.3.4")], "doc_id long, text string")
        began = time.time()
        spans = pii.find(df).first()["spans"]
        assert [(s["start"], s["kind"]) for s in spans] == [(5 * n, "ip")]
        return time.time() - began

    took(1_000)
    assert took(100_000) < 30 * max(took(10_000), 0.3)


def test_quality(docs, none, spark):
    from lossband.llm import quality

    labels = spark.createDataFrame([(4, 1), (4, 0), (9, 0), (None, 1), (7, None)], "doc_id long, quality int")
    forest = quality.fit_on(docs, labels)
    got = quality.with_score(docs, forest).collect()
    assert len(got) == len(DOCS) and all(0 <= r["score"] <= 1 for r in got) and dict(quality.with_score(docs, forest).dtypes)["score"] == "double"
    assert quality.with_score(none, forest).count() == 0
    odd = quality.with_score(docs.withColumnRenamed("row", "a`b"), forest, least=0.0)
    assert odd.count() == len(DOCS) and "a`b" in odd.columns and "score" in odd.columns
    assert 0 < quality.fit_on(docs, labels.where("1 = 0")).score(quality.np.zeros((2, len(quality.NAMES))))[0] < 1


def test_forest_learns_and_flattens():
    import numpy as np
    from lossband.llm import quality

    rng = np.random.default_rng(0)
    x = rng.standard_normal((2000, 3))
    y = ((x[:, 0] > 0.2) ^ (x[:, 1] > 0)).astype(float)
    f = quality.fit(x, y, trees=40)
    assert ((f.score(x) > 0.5) == y).mean() > 0.97
    one = []
    for row in x[:50]:  # node by node
        total = f.base
        for i in f.roots:
            while f.left[i] != i:
                i = f.left[i] if row[f.feature[i]] <= f.cut[i] else f.right[i]
            total += f.value[i]
        one.append(1 / (1 + np.exp(-total)))
    assert np.allclose(one, f.score(x[:50]))


def test_bpe(docs, none):
    import public_tokenizers as P
    from lossband.llm import byte_bpe

    path = P.path("byte_bpe_50k.tiktoken")
    coded = byte_bpe.encode_table(docs, path, P.PATTERN)
    got = coded.collect()
    assert len(got) == len(DOCS) and all(r["exact"] for r in got) and byte_bpe.encode_table(none, path, P.PATTERN).count() == 0
    back = {r["doc_id"]: r["text"] for r in byte_bpe.decode_table(coded, path, P.PATTERN).collect()}
    assert back[8] == DOCS[8][1] and back[1] == ""


def test_bpe_by_definition():
    import public_tokenizers as P
    from hypothesis import given, settings
    from hypothesis import strategies as st
    from lossband.llm.byte_bpe import ByteBPE

    with open(P.path("byte_bpe_50k.tiktoken"), "rb") as f:
        bpe = ByteBPE(f.read(), P.PATTERN)

    @settings(max_examples=150, deadline=None)
    @given(st.one_of(st.binary(min_size=1, max_size=60), st.text("aehilnorst ", min_size=1, max_size=60).map(str.encode)))
    def check(raw):
        assert bpe.cover(raw) == bpe.merge(raw)

    check()
    assert b"".join(bpe.cover(b"a" * 100_000)) == b"a" * 100_000


def test_ann(spark):
    from lossband.llm import ann

    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [1.0, 0.0]), (3, [0.0, 0.0]), (4, None), (5, [nan, 1.0]), (6, [inf, 1.0]), (7, [None, 1.0]), (8, []), (20, [0.5, 0.5]), (None, [1.0, 1.0]), (9, [1.0, 2.0, 3.0]), (40, [3.0, 2.0, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").selectExpr("*", "1 as id", "2 as v", "3 as rep", "4 as score")
    got = [tuple(r) for r in ann.nearest(df, df.where("vec_id % 20 = 0"), k=3).orderBy("query_id", "rank").collect()]
    assert got == [(0, 1, 1, 1.0), (0, 2, 2, 1.0), (0, 3, 20, 0.5), (20, 1, 0, 0.5), (20, 2, 1, 0.5), (20, 3, 2, 0.5), (40, 1, 9, 10.0)]
    assert ann.nearest(df.where("1 = 0"), df.where("1 = 0")).count() == 0


def test_exact(docs, none, spark):
    from lossband.llm import exact_dedup as ed

    got = sorted((r["doc_id"], r["keep_id"], r["group_size"], r["kept"]) for r in ed.exact_dedup(docs).collect() if r["doc_id"] is not None)
    assert (1, 2, 2, False) in got and (2, 2, 2, True) in got and (4, 6, 4, False) in got and (6, 6, 4, True) in got and got.count((8, 8, 2, True)) == 2 and (9, 10, 2, False) in got
    assert len(got) == len(DOCS) - 1 and ed.exact_dedup(none).count() == 0
    old = spark.createDataFrame([(100, "ONE"), (101, "else")], "doc_id long, text string")
    new = {r["doc_id"]: (r["keep_id"], r["kept"]) for r in ed.exact_dedup(docs, history=old).collect()}
    assert new[9] == (100, False) and new[10] == (100, False) and new[6] == (6, True) and new[4] == (6, False) and new[7] == (7, True)


def test_exact_members_come_from_the_index(spark, monkeypatch):
    """Below the history's ids only the index knows a winner: without its answers, repeats of history stand alone."""
    from lossband.llm import exact_dedup as ed

    docs = spark.createDataFrame([(i, f"text {i % 7}") for i in range(70)], "doc_id long, text string")
    got = {r["doc_id"]: (r["keep_id"], r["group_size"]) for r in ed.exact_dedup(docs).collect()}
    assert got == {i: (63 + i % 7, 10) for i in range(70)}
    real = ed.build_index
    monkeypatch.setattr(ed, "build_index", lambda scratch, seen, shards: real(scratch, seen.where("1 = 0"), shards))
    assert {r["keep_id"] for r in ed.exact_dedup(docs).where("doc_id < 30").collect()} != set(range(63, 70))


def test_exact_stage_with_repeated_ids(spark):
    """(5, A) is unique and stays though (5, B) is a copy; of equal rows of one id one stays."""
    import corpus_pipeline as p

    rows = [(5, "A only"), (5, "B text"), (6, "b TEXT"), (7, "seven"), (7, "seven"), (7, "SEVEN"), (None, "seven"), (None, "x")]
    docs = spark.createDataFrame([(i, t, "s") for i, t in rows], "doc_id long, text string, source string")
    for order in (docs, docs.orderBy("text", ascending=False)):
        got = sorted((r["doc_id"] or 0, r["text"]) for r in p.drop_copies(spark, order, "").collect())
        assert [x for x in got if x[0] != 7] == [(0, "seven"), (0, "x"), (5, "A only"), (6, "b TEXT")] and len([x for x in got if x[0] == 7]) == 1
    near = sorted((r["doc_id"] or 0, r["text"]) for r in p.drop_near_copies(spark, docs, "").collect())
    assert near == [(0, "seven"), (0, "x"), (5, "A only"), (5, "B text"), (7, near[-1][1])]


def test_perfect_hash():
    import hashlib

    import numpy as np
    from lossband.llm import exact_dedup as ed

    for n in (0, 1, 2, 1000):
        raw = np.frombuffer(b"".join(hashlib.sha256(str(i).encode()).digest() for i in range(n + 50)), np.uint8).reshape(-1, 32)
        sizes, bits, order = ed.build_hash(raw[:n])
        assert sorted(order) == list(range(n))
        at = ed.find(raw, sizes, bits, raw[order])
        assert (at[n:] == -1).all() and (order[at[:n]] == np.arange(n)).all()


def test_near(docs, none):
    from lossband.llm.near_dedup import near_dedup

    got = [(r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in near_dedup(docs, size=3, percent=85).collect()]
    by = {r[0]: r for r in got}
    assert len(got) == len(DOCS) and near_dedup(none).count() == 0
    assert by[1] == (1, 0, 1, True) and by[2] == (2, 0, 2, True) and by[3] == (3, 0, 3, True) and by[5] == (5, 1, 4, False) and by[10] == (10, 1, 9, False) and by[None] == (None, 1, None, True)
    assert got.count((8, by[8][1], 8, True)) == 2 and by[7][1] == 39_998


def test_near_group_with_chains(spark):
    """One large group whose members are linked by chains and pivots only, beside near misses."""
    from lossband.llm.near_dedup import near_dedup

    import random

    rng, base, docs = random.Random(5), [f"b{i}" for i in range(150)], []
    for i in range(240):
        words = list(base)
        for _ in range(rng.randrange(0, 9)):
            words[rng.randrange(150)] = f"x{i}_{rng.randrange(10**6)}"
        docs.append((i, " ".join(words)))
    words = list(base)
    for i in range(240, 300):
        words = list(words)
        words[rng.randrange(150)] = f"y{i}"
        docs.append((i, " ".join(words)))
    rng.shuffle(docs)
    for size, percent in ((3, 85), (5, 80)):
        want = brute.near_components(docs, size, percent)
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dedup(spark.createDataFrame(docs, "doc_id long, text string"), size=size, percent=percent).collect()}
        assert got == want


def _near(spark, docs, size, percent):
    from lossband.llm.near_dedup import near_dedup

    return [(r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in near_dedup(spark.createDataFrame(docs, "doc_id long, text string"), size=size, percent=percent).collect()]


def test_near_misses_of_one_template(spark):
    """Edits of one text, most of them too far from it and from one another; a few pairs share their edits and are linked."""
    import random

    rng, base, docs = random.Random(8), [f"b{i}" for i in range(150)], []
    edits = {}
    for i in range(400):
        words = list(base)
        if i % 10 == 9:  # shares all but one edit with an earlier text
            words = list(edits[rng.randrange(i // 10 * 10, i)])
            words[rng.randrange(150)] = f"z{i}"
        else:
            for j in range(rng.randrange(1, 14)):
                words[rng.randrange(150)] = f"x{i}_{j}"
            if i % 3 == 0:
                words = words[rng.randrange(20) :] + [f"y{i}_{j}" for j in range(rng.randrange(30))]
        edits[i] = words
        docs.append((i, " ".join(words)))
    rng.shuffle(docs)
    for size, percent in ((3, 85), (5, 80)):
        want = brute.near_components(docs, size, percent)
        assert {i: (n, c) for i, n, c, _ in _near(spark, docs, size, percent)} == want
        assert 5 < len({c for _, c in want.values()}) < 400


def test_near_pairs_far_from_their_representatives(spark):
    """Pairs of near copies whose lists name a long text that they share a third with."""
    import random

    rng, docs = random.Random(9), []
    common = [f"c{i}" for i in range(120)]
    for i in range(60):
        own = [f"o{i}_{j}" for j in range(rng.randrange(60, 260))]
        words = common[: rng.randrange(40, 120)] + own
        docs.append((2 * i, " ".join(words)))
        words = list(words)
        for _ in range(rng.randrange(0, 5)):
            words[rng.randrange(len(words))] = f"n{i}_{rng.randrange(99)}"
        docs.append((2 * i + 1, " ".join(words)))
    docs += [(1000 + i, " ".join(common + [f"e{i}_{j}" for j in range(3 * i)])) for i in range(20)]
    for size, percent in ((3, 85), (5, 80), (2, 60)):
        assert {i: (n, c) for i, n, c, _ in _near(spark, docs, size, percent)} == brute.near_components(docs, size, percent)


def test_near_ids_that_repeat(spark):
    """An id with two texts is one document: what is like either of them joins it, in whatever order the rows come."""
    a, b = [f"a{i}" for i in range(100)], [f"b{i}" for i in range(100)]
    rows = [(5, " ".join(a)), (5, " ".join(b)), (7, " ".join([*b[:-1], "x"])), (9, " ".join([*a[:-1], "y"])), (5, " ".join(a)), (11, "else")]
    for order in (rows, rows[::-1]):
        got = _near(spark, order, 5, 80)
        assert {(i, c) for i, _, c, _ in got} == {(5, 5), (7, 5), (9, 5), (11, 11)} and len(got) == 6


def test_mixing(docs, none):
    from lossband.llm import mixing

    rows, by = mixing.mix(mixing.words(docs))
    got = rows.collect()
    assert len(got) == len(DOCS) and all(r["taken"] <= 2 * r["size"] and (r["size"] or not r["taken"]) for r in got)
    assert [r["source"] for r in by.orderBy(by["source"].asc_nulls_last()).collect()] == ["a", "b", None]
    assert mixing.mix(mixing.words(none))[0].count() == 0


def test_mixing_of_overlapping_sources(spark):
    from lossband.llm import mixing

    rows = [(i, 10 + i % 7, [["a"], ["b"], ["a", "b"], ["b", "a"], ["a", None]][i % 5]) for i in range(500)]
    out, by = mixing.mix(spark.createDataFrame(rows, "doc_id long, size long, sources array<string>"), quotas={"a": 3000, "b": 2000, None: 500})
    taken = sum(r["taken"] for r in out.collect())
    assert 5500 - 30 <= taken <= 5500


def test_mixing_of_many_sources(spark):
    """As many sources as come: each near its target, and the targets those of the definition."""
    from lossband.llm import mixing

    docs = spark.range(20_000).selectExpr("id as doc_id", "1 + pmod(id * 7919, 97) as size", "array(concat('s', pmod(id, 5000))) as sources")
    rows, about = mixing.mix(docs)
    sizes = {r["sources"][0]: r["n"] for r in docs.groupBy("sources").agg({"size": "sum"}).withColumnRenamed("sum(size)", "n").collect()}
    want, got = brute.mix_targets(sizes), {r["source"]: r for r in about.collect()}
    assert len(got) == 5000 and all(abs(got[s]["target"] - float(want[s])) < 1e-6 * float(want[s]) and got[s]["quota"] == int(want[s]) for s in want)
    taken = dict.fromkeys(sizes, 0)
    for r in rows.collect():
        taken[r["sources"][0]] += r["taken"]
        assert r["taken"] in (0, r["size"], 2 * r["size"])
    assert all(0 <= got[s]["quota"] - taken[s] <= 97 for s in sizes)


def test_mixing_of_repeated_rows(spark):
    """A stage sees rows of one id with different texts and sources apart, and gives equal rows equal copies."""
    import corpus_pipeline as p

    rows = [(1, f"a{i} b c d", "x") for i in range(6)] + [(2, "same words here", "y")] * 4 + [(i, "w " * (i % 9), "z") for i in range(10, 200)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = [tuple(r) for r in p.mix_sources(spark, docs, "").collect()]
    assert set(got) <= set(rows) and len({got.count((2, "same words here", "y"))} & {0, 4, 8}) == 1
    total = sum(len(t.split()) for _, t, _ in rows)
    assert 0.9 * 1.5 * total <= sum(len(t.split()) for _, t, _ in got) <= 1.5 * total


def test_urls(spark):
    from lossband.llm import url_filter as uf
    from lossband.llm.queries import RULES

    link = '<link href="{}" rel="canonical">'
    rows = [
        (1, "http://bad.example.net/es/1", ""), (2, "http://alias.example.org/x", link.format("http://bad.example.net/es/1")), (3, "http://far.example.org/y", '<meta http-equiv="refresh" content="0; url=http://alias.example.org/x">'),
        (4, "http://good.example.com/fr/", link.format("http://alias.example.org/x")), (5, "http://www.example.com/en/z", None), (6, None, None), (7, "no-scheme", ""), (8, "HTTP://WWW.Example.COM", ""), (9, "http://ünï.example.org/?q=1", ""), (2, "http://alias.example.org/x", ""),
        (10, "https://far.example.org/y?utm_source=1#a", ""), (11, "http://never.example.org/", link.format("//x.net/fr/gone")),
    ]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 as host", "2 as node", "3 as path")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in uf.judge(pages, RULES).collect()}
    assert got[1][2:] == ("net/es/", "block") and got[2][2:] == (None, "block") and got[3][3] == "block" and got[10][3] == "block" and got[11][3] == "block"
    assert got[4][2:] == ("com/", "allow") and got[5][2:] == ("www.example.com/en/", "allow")
    assert got[6] == ("", "", None, "allow") and got[7] == ("", "", None, "allow") and got[8] == ("www.example.com", "", None, "allow")
    assert uf.judge(pages.where("1 = 0"), RULES).count() == 0
    for i, url, _ in rows:
        host, path, best = brute.url_row(url, RULES)
        assert got[i][:2] == (host, path) and got[i][2] == (best[1] if best else None)


def test_components(spark):
    import random

    from lossband.llm.common import Scratch, connected_components

    rng = random.Random(1)
    edges = [(i, i + 1) for i in range(60)] + [(100, i) for i in range(101, 160)] + [(rng.randrange(200, 400), rng.randrange(200, 400)) for _ in range(150)] + [(5, 5), (None, 3)]
    got = {r["node"]: r["component"] for r in connected_components(Scratch(spark, "t"), spark.createDataFrame(edges, "a long, b long")).collect()}
    parent = {}

    def root(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in edges:
        if a is not None and a != b:
            a, b = root(a), root(b)
            parent[max(a, b)] = min(a, b)
    assert got == {x: root(x) for x in list(parent)}


def test_licenses(spark):
    from lossband.llm import licenses as lc

    known = spark.createDataFrame([("A", "The Licence of the Copyright-Owner!\nUse it."), ("A2", "the license of the copyright holder use it"), ("E", ""), (None, "x"), ("N", None)], "name string, text string")
    docs = spark.createDataFrame([(1, "Copyright (c) 2020 Someone\nTHE LICENSE of the copyright owner:\n\n use   IT"), (2, None), (3, ""), (4, "prose\nThe licence of the copyright holder, use it\nmore"), (5, "other"), (1, "...")], "doc_id long, text string")
    got = sorted((r["doc_id"], r["licenses"], r["notices"]) for r in lc.scan(docs.selectExpr("*", "1 as row", "2 as form"), known).collect())
    assert got == [(1, [], []), (1, ["A", "A2"], []), (2, [], []), (3, [], []), (4, [], ["A", "A2"]), (5, [], [])]
    assert lc.scan(docs.where("1 = 0"), known).count() == 0


def test_licenses_of_entire_texts(spark):
    """Only the digest of the whole text says what a license text is, whatever its case, spelling, holder and line breaks."""
    from lossband.llm import licenses as lc
    from lossband.llm import queries
    from lossband.llm.license_texts import TEXTS

    known = queries.known_licenses(spark)
    texts = dict(TEXTS)
    docs = [
        (1, "Copyright (c) 2021 A. Body\n\n" + texts["MIT"]), (2, texts["BSD-3-Clause"].upper().replace(" ", "\n")), (3, texts["ISC"].replace("software", "softwares")), (4, texts["Zlib"].replace("acknowledgment", "acknowledgement")),
        (5, texts["MIT"] + " and more"), (6, texts["0BSD"]), (7, "(c) 1999 X. All rights reserved.\n" + texts["BSD-2-Clause"]),
    ]
    got = {r["doc_id"]: r["licenses"] for r in lc.scan(spark.createDataFrame(docs, "doc_id long, text string"), known).collect()}
    assert {i: "".join(x) for i, x in got.items()} == {1: "MIT", 2: "BSD-3-Clause", 3: "", 4: "Zlib", 5: "", 6: "0BSD", 7: "BSD-2-Clause"}


def test_html_tree_decides(spark):
    """Plain branches that repeat go, on hosts of two pages and inside articles; what differs, or only looks alike because articles are copies, stays."""
    from lossband.llm import html_text as h

    def two(i):
        return f"<body><div><p>Subscribe to our letter, all of you</p></div><article><h1>T{i}</h1><p>Text {i}</p><div><p>Shared line</p></div></article></body>"

    def many(i, note):
        return f"<body><div><div><h1>T{i}</h1><p>Text {i}</p><div class=x><p>{note}</p></div></div></div></body>"

    def inside(i):
        return f"<article><h1>T{i}</h1><p>Text {i}</p><div class=box>Read more of our stories</div><p>End {i % 3}</p></article>"

    rows = [(i, "http://two.org/", two(i)) for i in (1, 2)] + [(10 + i, "http://Many.org/", many(i, "same")) for i in range(3)] + [(20 + i, "http://free.org/", many(i, f"own {i}")) for i in range(3)]
    rows += [(30 + i, "http://in.org/", inside(i)) for i in range(9)] + [(50 + i, "http://copy.org/", "<div>menu</div><article><h1>Same</h1><p>article</p></article>") for i in range(9)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r["page_id"]: r["text"] for r in h.extract(pages).collect()}
    assert got[1] == "T1\nText 1\nShared line" and got[2] == "T2\nText 2\nShared line"
    assert got[11] == "T1\nText 1" and got[21] == "T1\nText 1\nown 1"
    assert got[34] == "T4\nText 4\nEnd 1" and got[55] == "menu\nSame\narticle"
    assert "Subscribe" in h.main_text(two(1)) and "same" in h.main_text(many(1, "same")) and "Read more" in h.main_text(inside(1))


def test_html_of_deep_pages_is_linear():
    import time

    from lossband.llm import html_text as h

    def took(n):
        page = "<table><tr><td>" * n + "x" + "</td></tr></table>" * n
        began = time.process_time()
        assert h.main_text(page) == "x" and len(h.elements(page)[1]) >= n
        return time.process_time() - began

    took(500)
    assert took(40_000) < 40 * max(took(4_000), 0.01)


def test_html(spark):
    from lossband.llm import html_text as h

    def page(i):
        return f"<html><head><title>t</title></head><body><header>Site</header><div class=top><p>Always the same {'x' * 30}</p></div><div id='c'><h1>Title {i}</h1><p>Body of &lt;page&gt; {i}<br>next&nbsp;line<p>Second {i * 7}</div><div class='sidebar'>s</div><form>f</form><div class=\"comments\"><p>c</p></div><footer>f</footer></body></html>"

    rows = [(i, "http://h.org/a", page(i)) for i in range(12)] + [(50, None, None), (51, "x", ""), (52, "http://one.org/", "<p>a<b>b</p>c <script>x</script> <div><p>d &amp; e"), (53, "http://one.org/", "<article><header><h1>T</h1></header>" + "<div>" * 3000 + "deep" + "</div>" * 3000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 as host", "2 as drop", "3 as text")
    got = {r["page_id"]: r["text"] for r in h.extract(pages).collect()}
    assert got[3] == "Title 3\nBody of <page> 3 next line\nSecond 21"
    assert got[50] == "" and got[51] == "" and got[52] == "ab\nc\nd & e" and got[53] == "T\ndeep"
    assert h.extract(pages.where("1 = 0")).count() == 0
    assert abs(h.importance([1] * 8, 8) - 1) < 1e-12 and h.importance([8], 8) == 0


def test_html_names_that_only_look_like_noise():
    from lossband.llm.html_text import main_text

    page = """<body><div class="layout with-sidebar"><div class="main-nav">menu</div><article style="overflow:hidden"><div class="entry-header"><h1>Title</h1></div>
        <p aria-hidden="false">One <a href="/hidden-gems">gem</a></p><p data-id="promo" data-class="ad">Two</p><p hidden>no</p><div class="share">no</div></article></div></body>"""
    assert main_text(page) == "Title\nOne gem\nTwo"


def test_stages(docs, none, spark):
    """Every stage keeps the columns it is given, whatever their names, and takes empty tables."""
    import corpus_pipeline as p

    sf = "/root/testdata/sf0.001"
    more = docs.selectExpr("*", "1 as gone", "2 as copies", "3 as copy", "4 as taken_id", "5 as n_chars")
    for name, stage in p.STAGES:
        out = stage(spark, more, sf)
        assert stage(spark, none, sf).count() == 0
        if name != "byte_bpe":
            assert out.columns == more.columns
        ids = sorted(r["doc_id"] for r in out.select("doc_id").collect() if r["doc_id"] is not None)
        if name == "exact_dedup":
            assert ids == [2, 3, 6, 7, 8, 10]
        if name == "near_dedup":
            assert ids == [1, 2, 3, 4, 7, 8, 9]
        if name == "byte_bpe":
            assert len(ids) == len(DOCS) - 1
