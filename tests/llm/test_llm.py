"""Each operator against brute force, held-out accuracy or an exact round trip, and on awkward tables."""

import re
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

pytest.importorskip("stagewise.llm.queries")

from stagewise.llm import components, exact_naming, host_reputation, html_extract, line_spread, minhash, mixing, packing, quality_cnn, queries, texthash, toxicity, vector_forest  # noqa: E402
from stagewise.llm.labelled import auc  # noqa: E402
from stagewise.store import Scratch  # noqa: E402

np.seterr(over="ignore")
DOCS = "doc_id long, text string, lang string, source string, gid int"  # an extra column whose name the operators use too
ODD = [(1, "a b c", "en", "x", 1), (2, None, None, None, 2), (3, "", "de", "x", None), (4, "A b C", "en", "y", 4), (1, "a b c", "en", "x", 1), (None, "a b c", "en", "x", 5),
       (6, "one", "en", "z", 6), (7, "w " * 30000 + "É ñ", "fr", "z", 7), (8, "  \n\t ", "es", "z", 8), (6, "other words here", "en", "z", 6)]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, DOCS)


def read(spark, sf, name):
    return spark.read.parquet(f"{sf}/{name}.parquet")


def test_words_and_shingles_equal_a_plain_reading():
    texts = ["a b\x0bc  d", "", None, "One", "É x É x É", "x" * 3_000_000 + " y", "\t", "A\rB\n" * 5]
    for width in (2, 5):
        _, sizes = texthash.shingle_sets(*texthash.text_bytes(pa.array(texts)), width)
        for t, n in zip(texts, sizes):
            w = re.findall(rb"[^\x20\x09-\x0d]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (t or "").encode()))
            assert n == (len({tuple(w[i : i + width]) for i in range(len(w) - width + 1)}) if len(w) >= width else int(bool(w)))


def alike(n=11):
    """Two words of 2,048 bytes whose polynomial hashes modulo 2**64 agree for every base."""
    x, y = "a", "b"
    for _ in range(n):
        x, y = x + y, y + x
    return x, y


def test_words_that_share_a_polynomial_hash_are_told_apart(spark):
    from tokenizers import Tokenizer

    x, y = alike()
    raw, offsets = texthash.text_bytes(pa.array([f"{x} {y}"]))
    a, b = texthash.span_hashes(raw, *texthash.word_spans(raw, offsets)).tolist()
    assert a == b and x != y
    rows = [(1, f"{x} {y} {x} {x}", "en", "s", 0), (2, f"{y} {x} {y} {y}", "en", "s", 0), (3, x, "en", "s", 0), (4, y, "en", "s", 0)]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in minhash.near_duplicates(spark.createDataFrame(rows, DOCS), 2).collect()}
    assert got == brute_components({r[0]: r[1] for r in rows}, 2) == {1: (3, 1), 2: (3, 2), 3: (1, 3), 4: (1, 4)}
    tokens, whole = packing.WordTokens(queries.tokenizer_path()), Tokenizer.from_file(queries.tokenizer_path())
    for text in (f"{x} {y}", y, "H\u0331 h\u0331 \u1e96 J\u030c \u01f0 W\u030a.", "I\u0307 \u0130 i\u0307, A\u030a"):
        assert tokens(pa.array([text]))[0].tolist() == whole.encode(text, add_special_tokens=False).ids


def test_sketch_estimates_similarity():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 2**63, 1000).astype(np.uint64)
    for keep in (990, 900, 500):
        other = np.concatenate([base[:keep], rng.integers(0, 2**63, 1000 - keep).astype(np.uint64)])
        s = texthash.similarity_sketch(np.concatenate([base, other]), np.array([1000, 1000]), 1020)
        assert abs((s[0] == s[1]).mean() - keep / (2000 - keep)) < 0.06
    one = texthash.similarity_sketch(base[:1], np.array([1, 0]), 255)
    assert (one[0] != np.iinfo(np.uint64).max).all() and (one[1] == np.iinfo(np.uint64).max).all()


def brute_components(texts, width, percent=80):
    sets = {}
    for i, t in texts.items():
        w = re.findall(rb"[^\x20\x09-\x0d]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (t or "").encode()))
        sets[i] = {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set())
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                c = len(sets[a] & sets[b])
                if 100 * c >= percent * (len(sets[a]) + len(sets[b]) - c):
                    x, y = find(a), find(b)
                    root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


@pytest.mark.parametrize("width", [2, 5])
def test_near_duplicates_equal_brute_force(spark, sf, width):
    docs = read(spark, sf, "documents")
    expected = brute_components({r["doc_id"]: r["text"] for r in docs.collect()}, width)
    got = minhash.near_duplicates(docs, width).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in got} == expected
    assert all(r["kept"] == (r["doc_id"] == r["component_id"]) for r in got)


def test_chain_of_near_copies_is_one_component(spark):
    words = [f"w{i}" for i in range(200)]
    chain = [(k, " ".join(words[4 * k : 4 * k + 100]), "en", "s", 0) for k in range(20)]
    big = [(100 + k, " ".join(words[:60] + [f"u{k}"] + words[61:150]), "en", "s", 0) for k in range(300)]
    docs = spark.createDataFrame(chain + big, DOCS)
    got = {r["doc_id"]: r["component_id"] for r in minhash.near_duplicates(docs, 2).collect()}
    assert got == {i: c for i, (_, c) in brute_components({r[0]: r[1] for r in chain + big}, 2).items()}


def test_odd_rows_of_near_duplicates(odd):
    got = minhash.near_duplicates(odd, 2).collect()
    assert len(got) == len(ODD)
    assert [r["component_id"] for r in got if r["doc_id"] is None] == [None]
    assert {r["component_id"] for r in got if r["doc_id"] in (1, 4)} == {1}
    kept = minhash.keep_one(odd, 2)
    assert kept.columns == odd.columns
    assert sorted((r["doc_id"] or -1) for r in kept.collect()) == [-1, 1, 2, 3, 6, 6, 7, 8]
    assert minhash.near_duplicates(odd.limit(0)).count() == 0


def test_components_of_random_graphs(spark):
    rng = np.random.default_rng(5)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 300, (250, 2))] + [(k, k + 1) for k in range(1000, 1060)]
    got = {r["id"]: r["root"] for r in components.connected_components(spark.createDataFrame(edges, "a long, b long"), Scratch(spark, "t")).collect()}
    root = {v: v for e in edges for v in e}
    changed = True
    while changed:
        changed = False
        for a, b in edges:
            m = min(root[a], root[b])
            changed |= root[a] != m or root[b] != m
            root[a] = root[b] = m
    assert got == {v: r for v, r in root.items() if any(v in e and e[0] != e[1] for e in edges)}


def test_names_follow_from_the_texts_alone(spark, sf):
    docs = read(spark, sf, "documents")
    names = [sorted((r["doc_id"], r["blocks"], r["name"]) for r in exact_naming.name_texts(d, Scratch(spark, "t"), 64).collect()) for d in (docs.coalesce(1), docs.repartition(7))]
    assert names[0] == names[1]


def test_naming_takes_time_in_proportion_to_the_text(spark):
    import time

    took = []
    for mb in (1, 1, 8):
        docs = spark.range(2).select(F.col("id").alias("doc_id"), F.expr(f"repeat('É some words of it ', {mb} * 52000)").alias("text"))
        begin = time.time()
        assert {r["group_size"] for r in exact_naming.exact_duplicates(docs).collect()} == {2}
        took.append(time.time() - begin)
    assert took[2] < 3 * took[1] + 5


def test_exact_naming(spark, sf, odd):
    docs = read(spark, sf, "documents")
    groups = defaultdict(list)
    lower = lambda t: re.sub("[A-Z]", lambda m: m[0].lower(), t or "")
    for r in docs.collect():
        groups[lower(r["text"])].append(r["doc_id"])
    expected = {i: (max(own), len(own), i == max(own)) for own in groups.values() for i in own}
    for size in (16, 1024):
        got = exact_naming.exact_duplicates(docs, size).collect()
        assert {r["doc_id"]: (r["keep_id"], r["group_size"], r["kept"]) for r in got} == expected
    weak = exact_naming.name_texts(docs, Scratch(spark, "t"), 64, lambda b: __import__("pyspark.sql.functions", fromlist=["x"]).length(b).cast("long")).collect()
    names = defaultdict(set)
    for r in weak:
        names[(r["blocks"], r["name"])].add(r["text_sha256"])
    assert all(len(x) == 1 for x in names.values()) and len(names) == len(groups)
    got = exact_naming.exact_duplicates(odd, 64).collect()
    assert len(got) == len(ODD) and sum(r["kept"] for r in got) == len({lower(r[1]) for r in ODD})
    kept = exact_naming.keep_one(odd, 64)
    assert kept.columns == odd.columns and kept.count() == len({lower(r[1]) for r in ODD})
    assert exact_naming.exact_duplicates(odd.limit(0)).count() == 0
    plan = docs.sparkSession.sql("select 1")._jdf.queryExecution().toString()
    assert "Python" not in plan


def test_main_text():
    page = """<html><head><title>T</title><script>var a="</p><p>no";</script></head><body><header>Site</header><nav><a href=x>Home</a></nav>
    <div class="cookie-notice">We use cookies to make this the best of all of the sites that you have been to.</div>
    <article><h1>Head &amp; line</h1><p>The <b>first</b> part of the text is here &lt;and&gt; it is long enough to be judged by the words that are in it, which are those of a text.<p>Short.
    <div class=comments><p>I like it.</p></div></article><aside>More</aside><form>Name <input></form><footer>&copy; us</footer></body></html>"""
    assert html_extract.main_text(page) == "Head & line The first part of the text is here <and> it is long enough to be judged by the words that are in it, which are those of a text. Short."
    for bad in (None, "", "<", "<p", "<!-- x", "<script>never closed <p>x", "plain"):
        assert isinstance(html_extract.main_text(bad), str)


PARAGRAPH = "The first part of the text is here and it is long enough to be judged by the words that are in it, which are those of a text that was written for it."


@pytest.mark.parametrize("page, text", [
    (f"<p><a href=x title=it's>Menu</a></p><p title=it's>{PARAGRAPH}</p>", PARAGRAPH),
    (f"<p data-x='>' class=\"x\">{PARAGRAPH}<p>a < b", PARAGRAPH + " a < b"),
    (f"<html><body><div><p>{PARAGRAPH[:125]}</p></div></body></html>", PARAGRAPH[:125].strip()),
    ("plain", "plain"),
    (f"<article class='post side'><p>{PARAGRAPH}</p></article>", PARAGRAPH),
    (f"<div class='layout with-sidebar'><p>{PARAGRAPH}</p></div>", PARAGRAPH),
    (f"<div class='right-sidebar'><article><p>{PARAGRAPH}</p></article><div class=sidebar><p>{PARAGRAPH} No.</p></div></div>", PARAGRAPH),
    (f"<div class='right-sidebar'><p>{PARAGRAPH}</p></div>", PARAGRAPH),
    (f"<div class='post has-comments hidden-xs'><p>{PARAGRAPH}</p><ol id=comment-list><li><article class=comment-body><p>{PARAGRAPH} I like it.</p></article></ol></div>", PARAGRAPH),
    (f"<div class='cookie-notice'><p>{PARAGRAPH}</p></div>", ""),
    (f"<p>{PARAGRAPH}</p><p>{' '.join(f'<a href={k}>Read of the other one</a>' for k in range(9))}</p><p>Short.</p><p>{PARAGRAPH}</p>", f"{PARAGRAPH} {PARAGRAPH}"),
])
def test_main_text_of_odd_pages(page, text):
    assert html_extract.main_text(page) == text


@pytest.mark.parametrize("tag", ["div", "p", "span", "li"])
def test_extraction_takes_time_in_proportion_to_the_page(tag):
    import time

    for page in ("<{0}>" * 40_000 + "x" + "</{0}>" * 40_000, "<{0}>x</q>" * 40_000, '<{0} x="\'' * 40_000):
        begin = time.time()
        html_extract.main_text(page.format(tag))
        assert time.time() - begin < 5


def test_rules_alone_find_the_articles(spark):
    """Pages without article or main elements: the two passes decide alone."""
    import html as H

    whole = found = same = n = 0
    for r in read(spark, "/root/testdata/sf0.1", "pages").collect():
        text = " ".join(H.unescape(re.sub(r"<[^>]+>", " ", re.search(r"<article>(.*?)</article>", r["html"], re.S)[1])).split())
        got = html_extract.main_text(re.sub(r"(</?)article>", r"\1div>", r["html"]))
        whole, found, same, n = whole + len(text), found + min(len(got), len(text)), same + (got == text), n + 1
    assert found >= 0.95 * whole and same >= 0.8 * n


def test_extraction_of_odd_tables(spark):
    rows = [(1, "u", None, 1), (2, None, "", 2), (None, "v", f"<p>{PARAGRAPH}</p>", 3), (1, "u", None, 1), (4, "w", "<p>x" * 50_000, 4)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, text int")
    got = html_extract.extract(pages).collect()
    assert sorted(r["n_chars"] for r in got) == [0, 0, 0, len(PARAGRAPH), 2 * 50_000 - 1]
    assert html_extract.extract(pages.limit(0)).count() == 0


def test_extraction_equals_the_articles(spark, sf):
    import html as H

    pages = read(spark, sf, "pages")
    got = {r["page_id"]: r for r in html_extract.extract(pages).collect()}
    for r in pages.collect():
        article = re.search(r"<article>(.*?)</article>", r["html"], re.S)[1]
        assert got[r["page_id"]]["text"] == " ".join(H.unescape(re.sub(r"<[^>]+>", " ", article)).split())
        assert got[r["page_id"]]["n_chars"] == len(got[r["page_id"]]["text"])


def test_best_fit_decreasing_and_windows():
    rng = np.random.default_rng(2)
    for _ in range(50):
        window = int(rng.choice([8, 64]))
        sizes = rng.integers(0, 3 * window, 30).tolist()
        seen = defaultdict(list)
        for own in packing.plan_windows(sizes, window):
            n = sum(x[2] for x in own)
            assert n == window or n & (n - 1) == 0
            for i, start, length in own:
                seen[i].append((start, length))
        for i, n in enumerate(sizes):
            at = 0
            for start, length in sorted(seen[i]):
                assert start == at
                at += length
            assert at == n


def test_packing_round_trip(spark, sf, odd):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(queries.tokenizer_path())
    for docs in (read(spark, sf, "documents"), odd.where("doc_id is not null and doc_id not in (1, 6)")):
        texts = {r["doc_id"]: r["text"] for r in docs.collect()}
        got = packing.pack(docs, queries.tokenizer_path()).collect()
        of = defaultdict(list)
        at = defaultdict(list)
        for r in got:
            of[r["doc_id"]].append(r)
            at[r["sequence_id"]].append((r["offset"], r["length"]))
        assert set(of) == set(texts)
        for i, text in texts.items():
            ids = np.array([*t.encode(text or "", add_special_tokens=False).ids, 2], dtype="<u4")
            place = 0
            for r in sorted(of[i], key=lambda r: r["start"]):
                assert r["start"] == place and r["doc_tokens"] == len(ids)
                assert r["ids_crc32"] == zlib.crc32(ids[place : place + r["length"]].tobytes())
                place += r["length"]
            assert place == len(ids)
        for own in at.values():
            place = 0
            for offset, length in sorted(own):
                assert offset == place
                place += length
            assert place == 4096 or place & (place - 1) == 0
    assert packing.pack(odd.limit(0), queries.tokenizer_path()).count() == 0


def test_quality_on_held_out_rows(spark):
    import pandas as pd

    d = "/root/testdata/sf0.01"
    got = quality_cnn.score(read(spark, d, "documents"), read(spark, d, "labels")).toPandas().merge(pd.DataFrame(read(spark, d, "labels").toPandas()), on="doc_id")
    held = got[got["held_out"]]
    assert auc(held["score"].to_numpy(), held["quality"].to_numpy()) > 0.95
    assert got["score"].between(0, 1).all()


def test_toxicity_on_held_out_rows(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = read(spark, d, "documents"), read(spark, d, "labels")
    got = toxicity.score(docs, labels).toPandas().merge(labels.toPandas()[["doc_id", "toxic"]].rename(columns={"toxic": "label"}), on="doc_id")
    held = got[[zlib.crc32(str(i).encode()) % 4 == 2 for i in got["doc_id"]]]
    toxic = held["label"] == 1
    assert held[toxic]["rejected"].mean() > 0.8 and held[~toxic]["rejected"].mean() < 0.01


def test_classifiers_on_odd_rows(spark, odd):
    labels = spark.createDataFrame([(1, 1, 0), (4, 0, 1), (None, 1, 1), (99, 1, 1), (6, None, None)], "doc_id long, quality int, toxic int")
    for some in (labels, labels.limit(0)):
        assert quality_cnn.score(odd, some).count() == len(ODD)
        assert toxicity.score(odd, some).count() == len(ODD)
    clean = toxicity.keep_clean(odd, labels.limit(0))
    assert clean.columns == odd.columns and clean.count() == len(ODD)
    assert quality_cnn.score(odd.limit(0), labels).count() == 0


def test_classifiers_beside_columns_of_the_same_names(spark):
    rows = [(k, ("good plain words here " if k % 2 else "bad junk %% && ") * 8, "en", "s", 0, 1.5, "x", 3, None) for k in range(60)]
    docs = spark.createDataFrame(rows, DOCS + ", quality double, toxic string, label int, shard binary")
    labels = spark.createDataFrame([(k, k % 2, 1 - k % 2, 0) for k in range(60)], "doc_id long, quality int, toxic int, text int")
    got = {r["doc_id"]: r["predicted"] for r in quality_cnn.score(docs, labels).collect()}
    assert got == {k: k % 2 for k in range(60)}
    assert sorted(r["doc_id"] for r in toxicity.keep_clean(docs, labels).collect()) == list(range(1, 60, 2))
    assert toxicity.keep_clean(docs, labels).columns == docs.columns


def test_fitting_reads_whole_texts(spark):
    """What tells the labels apart stands only in the middle of texts of 300,000 characters."""
    fill = "of the and to in a is that for it " * 4_300
    rows = [(k, fill + ("wonderful " if k % 2 else "zzqqxx%% ") * 20 + fill, "en", "s", 0) for k in range(48)]
    docs = spark.createDataFrame(rows, DOCS)
    labels = spark.createDataFrame([(k, k % 2, 1 - k % 2) for k in range(48)], "doc_id long, quality int, toxic int")
    got = {r["doc_id"]: r["score"] for r in quality_cnn.score(docs, labels).collect()}
    assert min(got[k] for k in range(1, 48, 2)) > max(got[k] for k in range(0, 48, 2))
    assert sorted(r["doc_id"] for r in toxicity.score(docs, labels).where("rejected").collect()) == list(range(0, 48, 2))


def test_gradients_of_the_net():
    rng = np.random.default_rng(4)
    net = quality_cnn.ByteNet()
    for k, v in net.p.items():
        net.p[k] = (v + 0.05 * rng.standard_normal(v.shape)).astype(np.float64)
    raw, offsets = texthash.text_bytes(pa.array(["some words of a text " * 60, "", "x", "other things " * 30]))
    labels = np.array([1, 0, 1, 0])

    def loss():
        net.pairs = None
        p = np.clip(net.score(raw, offsets), 1e-12, 1 - 1e-12)
        return -np.mean(labels * np.log(p) + (1 - labels) * np.log(1 - p))

    g = net.gradients(raw, offsets, labels)
    for k, at in (("table", (2, 111, 3)), ("table", (0, 32, 5)), ("b0", (4,)), ("w1", (3, 2)), ("b1", (1,)), ("w2", (6,)), ("b2", (0,))):
        old = net.p[k][at]
        net.p[k][at] = old + 1e-4
        up = loss()
        net.p[k][at] = old - 1e-4
        down = loss()
        net.p[k][at] = old
        assert g[k][at] == pytest.approx((up - down) / 2e-4, abs=2e-3, rel=0.05)


def test_rules_and_reputation(spark):
    pages = spark.createDataFrame([(1, "http://A.Example.NET/en/x?q"), (2, "http://example.net/de/"), (3, "http://b.org/fr/1"), (4, "http://example.com/de/1"), (5, None), (6, "nothing"), (7, "http://bad.example.com/x#y"), (8, "http://net"), (9, "http://notnet.com/")], "page_id long, url string")
    outcomes = spark.createDataFrame([("bad.example.com", 0)] * 60 + [("good.example.com", 1)] * 60 + [("notnet.com", 1)] * 3, "host string, good int")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in host_reputation.judge(pages, outcomes).collect()}
    assert got[1] == ("a.example.net", "/en/x", "example.net/en/", "allow")
    assert got[2][2:] == ("net/", "block") and got[3][2:] == ("org/fr/", "allow") and got[4][2:] == ("example.com/de/", "block")
    assert got[5] == got[6] == ("", "", None, "allow")
    assert got[7] == ("bad.example.com", "/x", None, "block") and got[8][2] is None and got[9][3] == "allow"
    assert host_reputation.judge(pages, outcomes.limit(0)).count() == 9
    assert host_reputation.judge(pages.limit(0), outcomes).count() == 0
    odd = spark.createDataFrame([(1, None, "a", 1.0, 2), (None, None, "b", 1.0, 2), (1, None, "a", 1.0, 2)], "page_id long, url string, host string, good double, suffix int")
    nulls = spark.createDataFrame([(None, 1), ("x.com", None)], "host string, good int")
    assert [tuple(r)[1:5] for r in host_reputation.judge(odd, nulls).collect()] == [("", "", None, "allow")] * 3


def test_vectors(spark, sf):
    v = read(spark, sf, "embeddings").limit(300).collect()
    rng = np.random.default_rng(1)
    base = np.array([r["embedding"] for r in v])
    near = base[:100] + rng.standard_normal((100, 64)) * 0.02
    rows = [(i, x.tolist(), 0) for i, x in enumerate(np.vstack([base, near, np.repeat(base[:1], 40, axis=0)]))]
    rows += [(9000, None, 0), (9001, [0.0] * 64, 0), (9002, [None] * 64, 0), (9003, [float("nan")] * 64, 0), (9004, [1.0], 0), (9005, [], 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, leaf int")
    got = {r["vec_id"]: r for r in vector_forest.near_vectors(df, part=50).collect()}
    x = np.array([r[1] for r in rows[:-6]], dtype=np.float32).astype(np.float64)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    links = ((x @ x.T) >= 0.9).sum(axis=1) - 1
    mine = np.array([got[i]["n_links"] for i in range(len(x))])
    assert (mine <= links).all() and mine.sum() >= 0.99 * links.sum()
    assert all(got[k]["n_links"] == 0 and got[k]["component_id"] == k for k in range(9000, 9006))
    assert vector_forest.near_vectors(df.limit(0)).count() == 0


def test_partitions_without_a_usable_vector(spark):
    kind = "vec_id long, embedding array<double>, n_links string"
    some = spark.createDataFrame([(1, [1.0, 0.0], "x"), (2, [1e300, 1e299], "x"), (3, [1e-300, 0.0], "x"), (4, [0.0, -1.0], "x")], kind).coalesce(1)
    none = spark.createDataFrame([(5, None, "x"), (6, [], "x"), (7, [None, 1.0], "x"), (8, [float("inf"), 1.0], "x"), (9, [0.0, -0.0], "x"), (None, [1.0, 0.0], "x")], kind).coalesce(1)
    got = {r["vec_id"]: tuple(r)[1:] for r in vector_forest.near_vectors(none.where("vec_id < 8").unionByName(some).unionByName(none)).collect()}
    assert got == {1: (2, 1, True), 2: (2, 1, False), 3: (2, 1, False), 4: (0, 4, True), **{k: (0, k, True) for k in range(5, 10)}, None: (0, None, False)}
    assert sorted(r["n_links"] for r in vector_forest.near_vectors(none).collect()) == [0] * 6


def test_recall_of_planted_pairs(spark):
    """8,000 vectors in 200 loose groups, a quarter of them with a copy at a cosine from 0.90 to 0.99, against brute force."""
    rng = np.random.default_rng(8)
    middles = rng.standard_normal((200, 64))
    base = middles[rng.integers(0, 200, 6400)] + 1.1 * rng.standard_normal((6400, 64))
    base /= np.linalg.norm(base, axis=1, keepdims=True)
    off = rng.standard_normal((1600, 64))
    off -= (off * base[:1600]).sum(axis=1, keepdims=True) * base[:1600]
    off /= np.linalg.norm(off, axis=1, keepdims=True)
    c = rng.uniform(0.9, 0.99, (1600, 1))
    x = np.concatenate([base, c * base[:1600] + np.sqrt(1 - c * c) * off]).astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    got = {r["vec_id"]: r for r in vector_forest.near_vectors(df).collect()}
    unit = x.astype(np.float64) / np.linalg.norm(x.astype(np.float64), axis=1, keepdims=True)
    links = (unit @ unit.T >= 0.9).sum(axis=1) - 1
    mine = np.array([got[i]["n_links"] for i in range(len(x))])
    assert links.sum() >= 3000 and (mine <= links).all() and mine.sum() >= 0.95 * links.sum()


@pytest.mark.parametrize("cosine", [0.90, 0.93, 0.95, 0.97])
def test_links_inside_a_dense_group(spark, cosine):
    """A third of all rows in one group of distinct near copies."""
    rng = np.random.default_rng(3)
    middle, rest = rng.standard_normal(64), rng.standard_normal((4000, 64))
    middle /= np.linalg.norm(middle)
    off = rng.standard_normal((2000, 64)) / 8
    group = np.sqrt(cosine) * middle + np.sqrt(1 - cosine) * off
    x = np.concatenate([group, rest]).astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    got = {r["vec_id"]: r for r in vector_forest.near_vectors(df, leaf=8, sample=1000, part=300).collect()}
    unit = x.astype(np.float64) / np.linalg.norm(x.astype(np.float64), axis=1, keepdims=True)
    near = unit @ unit.T >= 0.9
    links, mine = near.sum(axis=1) - 1, np.array([got[i]["n_links"] for i in range(len(x))])
    assert (mine <= links).all() and mine.sum() >= 0.999 * links.sum()
    assert cosine == 0.90 or (mine == links).all()
    assert {got[i]["component_id"] for i in range(2000) if links[i] > 50} == {0}


def test_a_ball_counts_links_across_its_rim(spark):
    """Chains of vectors from a dense spot outwards: links into the halo, to other balls and beyond are counted once."""
    rng = np.random.default_rng(5)
    a, b, c = np.linalg.qr(rng.standard_normal((64, 3)))[0].T
    turn = np.concatenate([rng.normal(0, 0.1, 200), rng.uniform(-1.5, 1.5, 200)])[:, None]
    x = np.cos(turn) * a + np.sin(turn) * b + 0.1 * rng.standard_normal((400, 1)) * c
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    links = (unit @ unit.T >= 0.9).sum(axis=1) - 1
    for sample in (40, 400):  # no splits: what the trees are left with is compared too
        got = {r["vec_id"]: r["n_links"] for r in vector_forest.near_vectors(df, sample=sample, part=200).collect()}
        assert [got[i] for i in range(400)] == links.tolist()


def test_trees_deeper_than_the_sample_reaches():
    rng = np.random.default_rng(11)
    base = rng.standard_normal((4000, 64))
    near = base[:2000] + 0.25 * rng.standard_normal((2000, 64))  # cosines of about 0.97
    unit = np.concatenate([base, near])
    unit /= np.linalg.norm(unit, axis=1, keepdims=True)
    f = vector_forest.Forest(unit[rng.permutation(len(unit))[:600]], 8, 48, vector_forest.SPILL, 7, least_depth=9)
    assert (f.upper, f.depth) == (4, 9)
    met, largest = np.zeros(2000, dtype=bool), 0
    for t in range(8):
        row, leaf = f.leaves(unit, t)
        assert len(np.unique(row)) == len(unit)  # every vector is in a leaf
        largest = max(largest, np.bincount(leaf).max())
        own = set(zip(row.tolist(), leaf.tolist()))
        met[[i - 4000 for i, n in own if i >= 4000 and (i - 4000, n) in own]] = True
    assert met.mean() >= 0.9
    assert largest < len(unit) / 16  # the sample alone would stop at 1/16 and its spill


def test_line_spread_is_exact(spark, odd):
    rows = [(k, f"common line\nonly {k}\n\ncommon line", "en", f"s{k % 12}", 0) for k in range(40)] + [(100 + k, "rare line", "en", f"s{k % 9}", 0) for k in range(30)]
    got = {r["doc_id"]: r for r in line_spread.remove_boilerplate(spark.createDataFrame(rows, DOCS)).collect()}
    assert got[0]["text"] == "common line\nonly 0\n\ncommon line" and got[5]["text"] == "only 5\n" and got[5]["n_removed"] == 2
    assert all(got[100 + k]["text"] == "rare line" for k in range(30))
    assert line_spread.remove_boilerplate(odd).count() == len(ODD) and line_spread.remove_boilerplate(odd.limit(0)).count() == 0


def test_mixing_of_more_sources_than_a_driver_lists(spark, monkeypatch):
    docs = spark.range(100_200).selectExpr("id as doc_id", "if(id % 50 = 0, 'a b', 'a') as text", "concat('host', id) as source")
    plan = mixing.plan_mix(docs.unionByName(docs.limit(1).withColumn("source", F.lit(None).cast("string"))), most_repeated=2.5)
    r = plan.agg(F.count_if(F.col("pass") == 0).alias("n"), F.min("passes").alias("least"), F.count("*").alias("all"), F.countDistinct("source").alias("sources")).first()
    assert (r["n"], r["least"], r["sources"]) == (100_201, 1, 100_200) and r["all"] == 2 * 98_196 + 2_005
    few = spark.range(900).selectExpr("id as doc_id", "repeat('w ', cast(id % 9 as int)) as text", "nullif(cast(floor(sqrt(id % 100)) as string), '3') as source")
    want = sorted(map(tuple, mixing.plan_mix(few, target_entropy=2.2).collect()), key=str)
    monkeypatch.setattr(mixing, "FEW_SOURCES", 0)
    assert sorted(map(tuple, mixing.plan_mix(few, target_entropy=2.2).collect()), key=str) == want
    totals = [r["t"] for r in few.groupBy("source").agg(F.sum(mixing.token_count(F.col("text"))).alias("t")).collect()]
    shares = [t / sum(totals) for t in totals]
    told = spark.createDataFrame([(t,) for t in totals], "total long")
    for goal in ({"target_entropy": 2.2}, {"most_repeated": 1.7}, {"target_entropy": 2.2, "most_repeated": 1.7}, {}):
        assert mixing.solve_totals(told, **goal) == pytest.approx(mixing.solve_exponent(shares, **goal), abs=1e-9)


def test_mixing(spark, odd, monkeypatch):
    shares = [0.6, 0.3, 0.1]
    e = mixing.solve_exponent(shares, target_entropy=1.0)
    assert abs(mixing.entropy(mixing.weights(shares, e)) - 1.0) < 1e-6
    assert max(mixing.repetitions(shares, mixing.solve_exponent(shares, most_repeated=2.0))) == pytest.approx(2.0)
    rows = [(k, "w " * (1 + k % 7), "en", "big" if k % 10 else "small", 0) for k in range(4000)]
    docs = spark.createDataFrame(rows, DOCS)
    for few in (4096, 50):  # one range of ranks, many
        monkeypatch.setattr(mixing, "RANGE_ROWS", few)
        got = mixing.plan_mix(docs, most_repeated=1.5, block_tokens=2000).toPandas()
        assert len(got[got["pass"] == 0]) == 4000 and (got.groupby("doc_id")["pass"].apply(sorted) == got.groupby("doc_id")["passes"].first().map(lambda n: list(range(n)))).all()
        small = got[got["source"] == "small"]
        assert len(got[got["source"] == "big"]) == 3600
        # brute force: the last pass is the longest beginning of the permuted order within the budget
        once = small[small["pass"] == 0].sort_values("rank")
        again = set(once["doc_id"][once["tokens"].cumsum() <= once["tokens"].sum() // 2])
        assert set(small.loc[small["pass"] == 1, "doc_id"]) == again
        # every block is a permutation of its own with both sources near their weights
        assert (got.groupby("block")["position"].apply(lambda x: sorted(x) == list(range(len(x))))).all()
        weight = small["tokens"].sum() / got["tokens"].sum()
        blocks = got.groupby("block")["tokens"].sum()
        assert len(blocks) == -(-got["tokens"].sum() // 2000) and blocks.between(1500, 2500).all()
        assert (small.groupby("block")["tokens"].sum() / blocks).between(weight / 2, weight * 2).all()
    assert mixing.plan_mix(odd).where("pass = 0").count() == len(ODD) and mixing.mix(odd).columns == odd.columns
    assert mixing.mix(odd).distinct().count() == odd.distinct().count() and mixing.mix(odd.limit(0)).count() == 0
    clash = docs.withColumns({c: F.lit(c) for c in ("rank", "tokens", "s", "passes", "block", "whole", "cut", "part", "es")})
    for n in ("3", "8"):  # whole blocks lie in a task, in order
        spark.conf.set("spark.sql.shuffle.partitions", n)
        out = mixing.mix(clash, most_repeated=1.5, block_tokens=2000).withColumn("at", F.spark_partition_id())
        assert out.select("at").distinct().count() == int(n) and out.columns[:-1] == clash.columns
    plan = {(r["doc_id"], r["pass"]): r["block"] for r in mixing.plan_mix(docs, most_repeated=1.5, block_tokens=2000).collect()}
    read_in, seen = defaultdict(list), defaultdict(int)
    for r in out.select("doc_id", "at").collect():
        read_in[r["at"]].append(r["doc_id"])
    once = {i: b for (i, p), b in plan.items() if (i, 1) not in plan}
    for ids in read_in.values():
        order = [once[i] for i in ids if i in once]
        assert order == sorted(order)
        seen.update({b: seen[b] + 1 for b in set(order)})
    assert set(seen.values()) == {1}
    shown = mixing.mix(docs, most_repeated=1.5, block_tokens=2000).groupBy("doc_id").count().collect()
    assert {r["doc_id"]: r["count"] for r in shown} == got.groupby("doc_id").size().to_dict()


def test_pipeline_keeps_clean_documents(spark):
    import corpus_pipeline

    d = "/root/testdata/sf0.01"
    docs = read(spark, d, "documents")
    now = docs
    scratch = Scratch(spark, "t")
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES[:-1]):
        now = scratch.save(stage(spark, now, d), str(k))
        assert now.columns == docs.columns
        if k == 1:
            exact = {r["doc_id"] for r in now.collect()}
        if k == 2:
            found = {r["doc_id"]: r["text"] for r in now.collect()}
            assert set(found) <= exact and all(c == i for i, (_, c) in brute_components(found, 5).items())
        if k == 3:
            assert {r["doc_id"] for r in now.collect()} == set(found)
    assert {r["doc_id"] for r in corpus_pipeline.STAGES[-1][1](spark, now, d).collect()} == set(found)


def test_sql_queries(spark):
    import duckdb
    import pyarrow.dataset as ds

    d = "/root/testdata/sf0.001"
    con = duckdb.connect()
    for t in ("documents", "pages", "labels"):
        con.register(t, ds.dataset(f"{d}/{t}.parquet").to_table())
    for name, sql in queries.oracle_sql().items():
        got = queries.queries()[name](spark, d)
        expected = con.sql(f"select {', '.join(got.columns)} from ({sql})").fetchall()
        assert sorted(map(str, map(tuple, got.collect()))) == sorted(map(str, expected)), name
