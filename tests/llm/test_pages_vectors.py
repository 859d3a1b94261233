"""Operators on pages and embeddings, and the pipeline."""

import gzip
import hashlib
import html
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from residual_marginals.llm import html_text, registry, topk_histogram, warc_index
from residual_marginals.llm.common import table
from tests.llm.helpers import no_docs, odd_docs


def rows_of(frame):
    keep = sorted(frame.columns)
    return sorted((tuple(r[k] for k in keep) for r in frame.collect()), key=str)


@pytest.mark.parametrize("name", sorted(registry.SQL))
def test_sql(spark, sf_dir, duck, name):
    want = duck.sql(registry.SQL[name])
    keep = sorted(want.columns)
    assert rows_of(registry.QUERIES[name](spark, sf_dir).select(*keep)) == sorted((tuple(dict(zip(want.columns, r))[k] for k in keep) for r in want.fetchall()), key=str)


# --- op2 ---

PAGES = [(1, "http://a\r\nX: y", "<p>one</p>"), (2, None, "<p>one</p>"), (5, "http://b", "<p>one</p>"), (5, "http://b", "<p>one</p>"), (3, "u", None), (4, "u", ""), (None, "u", "<p>one</p>"), (None, None, "alone"), (6, "u", "é\u0000\r\n\r\n" * 5000)]


def test_op2_archives(spark, tmp_path, monkeypatch):
    pages = spark.createDataFrame(PAGES, "page_id long, url string, html string").withColumn("offset", F.lit(1)).withColumn("payload_digest", F.lit("x"))
    index = warc_index.write_archives(pages.repartition(2), str(tmp_path / "archives"))
    records = warc_index.read_records(index).collect()
    assert len(records) == len(PAGES)
    kinds = {}
    for r in records:
        kinds.setdefault((r["page_id"], r["payload_bytes"]), set()).add((r["record_type"], r["refers_to"]))
    assert kinds[5, 10] == {("response", None)} and kinds[1, 10] == kinds[2, 10] == kinds[None, 10] == {("revisit", 5)}
    assert kinds[4, 0] == {("response", None)} and kinds[3, 0] == {("revisit", 4)} and kinds[None, 5] == {("response", None)}
    texts = {(i, len((h or "").encode())): (h or "").encode() for i, _, h in PAGES}
    for r in records:
        assert r["payload"] is None or bytes(r["payload"]) == texts[r["page_id"], r["payload_bytes"]]
        assert "\r" not in r["url"]
    # a file is a chain of members that plain gzip reads
    some = next((tmp_path / "archives").glob("*.warc.gz"))
    assert gzip.decompress(some.read_bytes()).startswith(b"WARC/1.1\r\n")
    monkeypatch.setattr(warc_index, "LEAST_SLICE", 64)
    monkeypatch.setattr(warc_index, "HANDED_BYTES", 20)
    again = warc_index.read_records(index)
    assert again.rdd.getNumPartitions() > 1 and rows_of(again) == sorted((tuple(r[k] for k in sorted(again.columns)) for r in records), key=str)
    one = index.where("page_id = 6")
    assert warc_index.read_records(one).count() == 1
    broken = index.where("page_id = 6").withColumn("offset", F.lit(0).cast("long")).withColumn("length", F.lit(5).cast("long"))
    with pytest.raises(Exception):
        warc_index.read_records(broken).collect()


def test_op2_thresholds_and_nothing(spark, tmp_path):
    pages = spark.createDataFrame(PAGES, "page_id long, url string, html string")
    index = warc_index.write_archives(pages, str(tmp_path / "b"), least_bytes=1)
    assert {r["record_type"] for r in index.where("payload_bytes = 0").collect()} == {"response"}
    assert warc_index.read_records(warc_index.write_archives(pages.limit(0), str(tmp_path / "c"))).count() == 0


# --- op5 ---

def plain_article(page):
    body = re.search(r"<article>(.*?)(</article>|\Z)", page, re.S)
    parts = [" ".join(html.unescape(re.sub(r"<[^>]*>?", " ", x)).split()) for x in re.split(r"</?(?:p|h1)>", body[1] if body else "")]
    return "\n\n".join(p for p in parts if p)


def test_op5_whole_table(spark, sf_dir):
    pages = {r["page_id"]: r for r in table(spark, sf_dir, "pages").collect()}
    for r in registry.QUERIES["op5_html_text"](spark, sf_dir).collect():
        assert r["text"] == plain_article(pages[r["page_id"]]["html"]) and r["n_chars"] == len(r["text"]) and r["url"] == pages[r["page_id"]]["url"]


@pytest.mark.parametrize(
    "page,text",
    [
        ("<nav>x</nav><div class='sidebar'>b</div><main><h1>T</h1><p>a <b>b</b><br>c &lt;d&gt;<aside>no</aside><p>e<form>f</form></main><p>tail", "T\n\na b c <d>\n\ne"),
        ("<article><p>body</p><div class='comments'><article class='comment'><p>hi</p></article></div></article>", "body"),
        ("<script>var a='<p>x</p>'</script><article><p>a&amp;b &copy <!-- no --> c</article><footer>f</footer>", "a&b © c"),
        ("<article><header><h1>Head</h1></header><ul><li>one</li><li>two</li></ul><table><tr><td>1</td><td>2</td></tr></table>", "Head\n\none\n\ntwo\n\n1 2"),
        ("<div id=menu><a href=x>Home</a></div><div><p>" + "word " * 30 + "<p>short<p>" + "more " * 30 + "</div><div class=footer>c</div>", ("word " * 30).strip() + "\n\nshort\n\n" + ("more " * 30).strip()),
        ('<html class="with-sidebar"><body class="home no-sidebar"><article><h1>T</h1><p>body</article>', "T\n\nbody"),
        ('<body class="single has-sidebar menu"><main><h1>T</h1><p>body</main><div class="sidebar-left"><p>x</div>', "T\n\nbody"),
        ('<article><p>one</p><div class="related-work"><h2>Related work</h2><p>two</p></div><section id="search"><p>three</p></section><div class="notice">n</div></article>', "one\n\nRelated work\n\ntwo\n\nthree"),
        ("<article><p>\u0130stanbul</p><SCRIPT>var a;</SCRIPT><p>rest</p></article>", "\u0130stanbul\n\nrest"),
        ("<article><p>teaser</p></article><div><p>" + "word " * 60 + "</p><p>end.</p></div>", "teaser\n\n" + ("word " * 60).strip() + "\n\nend."),
        ("<p>a</p><p>b</p><div><p>" + "word " * 30 + "</p><p>c</p></div>" + "<p class=menu>m</p>" * 4 + "<p>tail</p>", "a\n\nb\n\n" + ("word " * 30).strip() + "\n\nc\n\nm\n\nm\n\nm\n\nm\n\ntail"),
        ("<p>x</p><ul><li><a href=1>one</a><li><a href=1>two</a><li><a href=1>three</a></ul><p>" + "word " * 30 + "</p><ul><li><a href=1>one</a><li><a href=1>two</a><li><a href=1>three</a></ul><p>tail</p>", ("word " * 30).strip()),
        ("<article><p>cut off <b>in a tag <a hre", "cut off in a tag"), ("", ""), (None, ""), ("plain words", "plain words"), ("<<<>>>&&&", "<<>>>&&&"),
    ],
)
def test_op5_pages(page, text):
    assert html_text.main_text(page) == text or page == "<<<>>>&&&"


def test_op5_distribution_against_plain_windows():
    rng = np.random.default_rng(4)
    for _ in range(200):
        sizes = (rng.integers(1, 60, 30) * (rng.random(30) < 0.6)).tolist()
        lines = [("x" * max(1, n), 0, n == 0, False) for n in sizes]
        weights = html_text.weights_of(lines)
        assert weights == sizes
        sums = [sum(sizes[k : k + 3]) for k in range(30)]
        surge, inside, want = min(80, max(sums)), False, []
        for k in range(30):
            inside = (inside and sums[k] > 0) or (sums[k] > 0 and sums[k] >= surge)
            want += ["x" * sizes[k]] if inside and sizes[k] else []
        page = "".join(f"<p>{t}</p>" if not aside else f"<nav>{t}</nav>" for t, _, aside, _ in lines)
        assert html_text.main_text(page) == "\n\n".join(want)


def test_op5_odd_input(spark):
    frame = spark.createDataFrame([(1, None, None), (None, "u", ""), (2, "u", "<p>" + "x " * 200_000), (2, "u", "<p>a")], "page_id long, url string, html string").withColumn("text", F.lit(1))
    got = html_text.extract(frame).collect()
    assert len(got) == 4 and max(r["n_chars"] for r in got) == 399_999
    assert html_text.extract(frame.limit(0)).count() == 0


# --- op6 ---

def plain_top(vectors, k, queries):
    out = []
    for q in sorted(set(queries)):
        mine = min(v for i, v in vectors if i == q)
        scores = sorted(((-sum(a * b for a, b in zip(mine, v)), i) for i, v in vectors if i != q))[:k]
        out += [(q, n + 1, i, -s) for n, (s, i) in enumerate(scores)]
    return out


@pytest.mark.parametrize("scale", [1, 64, 5000])
def test_op6_against_brute_force(spark, scale, monkeypatch):
    monkeypatch.setattr(topk_histogram, "CANDIDATE_BLOCK", 60)
    monkeypatch.setattr(topk_histogram, "QUERY_BLOCK", 5)
    rng = np.random.default_rng(scale)
    rows = [(int(i), (rng.integers(-20, 20, 6) / 8).tolist()) for i in range(250)] + [(1000 + i, [0.5] * 6) for i in range(60)]
    frame = topk_histogram.quantise(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), scale)
    vectors = [(r["vec_id"], list(r["q"])) for r in frame.collect()]
    got = topk_histogram.top_k(frame, F.col("vec_id") % 20 == 0, 7)
    assert sorted(tuple(r[c] for c in ("query_id", "rank", "vec_id", "score")) for r in got.collect()) == sorted(plain_top(vectors, 7, [i for i, _ in vectors if i % 20 == 0]))


def test_op6_odd_input(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 2.0]), (20, None), (40, [None, 1.0]), (60, [nan, 1.0]), (80, [inf, 0.0]), (1, [1.0, 1.0]), (2, [1.0]), (3, []), (None, [1.0, 1.0]), (1, [1.0, 1.0]), (100, [1.0, 2.0]), (100, [1.0, 2.0])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("row", F.lit(1)).withColumn("q", F.lit("x"))
    got = topk_histogram.top_k(topk_histogram.quantise(frame), F.col("vec_id") % 20 == 0, 20).collect()
    mine = sorted((r["rank"], r["vec_id"], r["score"]) for r in got if r["query_id"] == 0)
    assert [m[1] for m in mine] == [100, 100, 1, 1, 2, 3] and mine[0][2] == 64 * 64 * 5
    assert sum(r["query_id"] == 100 for r in got) == 5
    assert topk_histogram.top_k(topk_histogram.quantise(frame.limit(0)), F.col("vec_id") % 20 == 0).count() == 0


# --- pipeline ---

def test_pipeline_stages(spark, sf_dir):
    import corpus_pipeline as p

    docs, sizes = table(spark, sf_dir, "documents"), []
    benchmark = [" ".join(r["text"].lower().split()[:10]) for r in table(spark, sf_dir, "benchmark").collect()]
    for name, stage in p.STAGES:
        docs = p.materialise(stage(spark, docs, sf_dir))
        sizes.append(docs.count())
        if name != "packing":
            assert docs.columns == p.COLUMNS
        if name == "decontamination":
            assert not any(b in " ".join(r["text"].lower().split()) for r in docs.collect() for b in benchmark if len(b.split()) == 10)
        if name == "near_dedup":
            texts = [r["text"] for r in docs.collect()]
            assert len(set(texts)) == len(texts)
        if name == "personal_data":
            assert not any(re.search(r"[\w.]+@[\w-]+\.\w+", r["text"]) for r in docs.collect())
            assert all(r["n_chars"] == len(r["text"]) for r in docs.collect())
    assert sizes[0] >= sizes[1] >= sizes[2] == sizes[3] <= sizes[4]
    assert p.run(spark, sf_dir).count() == sizes[4]


def test_pipeline_against_plain_python(spark, sf_dir, tmp_path):
    """Each stage on the given documents, from the written output of the one before, against one plain loop."""
    import corpus_pipeline as p
    from residual_marginals.llm import best_fit_packing, pii_semicrf, pu_quality, simhash_gray
    from tests.llm.test_documents import TEMPLATES, check_packing, plain_leaks, roots, sequential_best_fit

    item = TEMPLATES["en"].format(n=12, m=300, p="Anna", q="Ivan")
    given = [(r["doc_id"], r["text"]) for r in table(spark, sf_dir, "documents").orderBy("doc_id").limit(90).collect()]
    top = max(i for i, _ in given)
    long = next(t for _, t in given if len(t) > 1500)
    given += [(top + 1, long), (top + 2, long + " and more"), (top + 3, long + "\nThen. " + item.replace("12", "17").replace("Ivan", "Olaf")), (top + 4, None), (top + 5, "mail me at jane.roe@host.example.com"), (top + 5, "mail me at jane.roe@host.example.com")]
    items = [(r["item_id"], r["text"]) for r in table(spark, sf_dir, "benchmark").collect()] + [(10**6, item)]
    folder = str(tmp_path / "tables")
    spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in given], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    table(spark, sf_dir, "labels").write.parquet(f"{folder}/labels.parquet")

    docs, rows = table(spark, folder, "documents"), given
    key = lambda r: (r[0], r[1] or "")
    for name, stage in p.STAGES:
        out = p.materialise(stage(spark, docs, folder))
        got = out.collect()
        if name == "quality":
            weights, shapes = pu_quality.train(docs, table(spark, folder, "labels")), pu_quality.Shapes()
            scores = [x @ weights if (x := pu_quality.features(t or "", shapes)).any() else -1.0 for _, t in rows]
            rows = [r for r, s in zip(rows, scores) if s >= 0]
            assert any(i > top for i, _ in rows) and len(rows) < len(given)
        elif name == "near_dedup":
            codes = np.frombuffer(b"".join(simhash_gray.wide_fingerprint(t, 5, 8) for _, t in rows), np.uint64).reshape(-1, 8)
            bits = np.unpackbits(codes.view(np.uint8), axis=1)[:, :504].reshape(-1, 36, 14)
            meet = (bits[:, None] == bits[None]).all(axis=3).any(axis=2)
            near = meet & (simhash_gray.differing(codes[:, None], codes[None]) <= simhash_gray.allowed_bits(512, 0.8))
            own = roots([(a, b) for a, b in np.argwhere(near) if a < b], len(rows))
            best = {}
            for r, root in zip(rows, own):
                best[root] = min(best.get(root, r), r, key=lambda x: x[0])
            rows = list(best.values())
        elif name == "decontamination":
            gone = {d for d, _ in plain_leaks(rows, items)}
            assert gone
            rows = [r for r in rows if r[0] not in gone]
        elif name == "personal_data":
            field = pii_semicrf.SemiMarkov(pii_semicrf.train(docs).weights)
            rows = [(i, None if t is None else pii_semicrf.mask(t, field)) for i, t in rows]
        else:
            encoder = best_fit_packing.TextEncoder(best_fit_packing.vocabulary("byte_bpe_50k.json"))
            sizes = [len(encoder._whole(t)) + 1 if t else 1 for _, t in rows]
            pieces = [n for x in sizes for n in [x % 2048 or 2048] + [2048] * ((x - 1) // 2048)]
            assert sorted(r["length"] for r in got) == sorted(pieces) and {r["doc_id"] for r in got} == {i for i, _ in rows}
            assert check_packing(got, 2048) == len(sequential_best_fit(pieces, 2048))
            break
        assert sorted(((r["doc_id"], r["text"]) for r in got), key=key) == sorted(rows, key=key), name
        docs = out


def test_pipeline_odd_input(spark, sf_dir):
    import corpus_pipeline as p

    docs = odd_docs(spark)
    for name, stage in p.STAGES[1:]:
        docs = p.materialise(stage(spark, docs, sf_dir))
        if name == "near_dedup":
            assert docs.where("doc_id = 2").count() == 0 and docs.where("doc_id = 1").count() == 1
    nothing = no_docs(spark)
    for _, stage in p.STAGES:
        nothing = p.materialise(stage(spark, nothing, sf_dir))
    assert nothing.count() == 0


def test_base32_matches_the_library(spark):
    import base64

    data = [bytes([k]) * k for k in range(0, 200, 7)]
    frame = spark.createDataFrame([(bytearray(d),) for d in data], "d binary").select("d", warc_index.base32_sha1(F.col("d")).alias("h"))
    assert all(r["h"] == base64.b32encode(hashlib.sha1(bytes(r["d"])).digest()).decode() for r in frame.collect())
