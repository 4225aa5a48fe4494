"""Classifiers by held-out accuracy, archives by round trip, search by brute force, rendering by example."""

import hashlib
import random

import numpy as np
import pytest

from catchment.llm import hamming_search, html_text, language_id, quality, warc

SF = "/root/testdata/sf0.01"


def test_language_held_out(spark):
    rows = language_id.op8_language_id(spark, SF).join(spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "lang"), "doc_id").filter("held_out").collect()
    assert np.mean([r["lang"] == r["lang_pred"] for r in rows]) > 0.97
    assert all(0 <= r["score"] <= 1 for r in rows)


def test_language_odd_rows(spark):
    docs = spark.createDataFrame([(i, t, lang, 1.0, "z") for i, (t, lang) in enumerate([(None, "a"), ("", "a"), ("12 !", "b"), ("the cat sat", "a"), ("le chat noir", "b"), ("x" * 200_000, "a"), ("the cat", None)])] + [(None, "the cat", "a", 1.0, "z")], "doc_id long, text string, lang string, score double, lang_pred string")
    told = {r["doc_id"]: r for r in language_id.identify(docs, language_id.fit_languages(docs)).collect()}
    assert [told[i]["lang_pred"] for i in (0, 1, 2)] == ["und"] * 3 and told[0]["score"] == 0
    assert all(told[i]["lang_pred"] in ("a", "b") for i in (3, 4, 5, 6, None))
    kept = language_id.drop_unidentified(docs)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} >= {3, 4, 5}
    blank = docs.filter("lang = 'none'")
    assert language_id.identify(docs, language_id.fit_languages(blank)).filter("lang_pred <> 'und'").count() == 0
    assert language_id.drop_unidentified(blank).count() == 0


def test_codewords_are_apart():
    for n in (1, 2, 4, 5, 9, 20):
        code = language_id.codewords(n)
        assert len(code) == n
        apart = [(code[i] != code[j]).sum() for i in range(n) for j in range(i)]
        assert not apart or min(apart) >= (1 if n < 3 else 2)


def test_quality_held_out(spark):
    rows = quality.op9_quality(spark, SF).join(spark.read.parquet(f"{SF}/labels.parquet"), "doc_id").filter("held_out").collect()
    assert np.mean([r["predicted"] == r["quality"] for r in rows]) > 0.9
    assert np.mean([r["predicted"] for r in rows if r["quality"] == 1]) > 0.97


def test_quality_odd_rows(spark):
    docs = spark.createDataFrame([(1, None, 0.3), (2, "", 0.3), (3, "a good plain text", 0.3), (4, "a", 0.3), (None, "b c", 0.3), (3, "long " * 50_000, 0.1)], "doc_id long, text string, score double")
    labels = spark.createDataFrame([(3, 1), (3, 1), (1, 0), (2, None), (4, 7)], "doc_id long, quality int")
    for marks in (labels, labels.limit(0)):
        rows = quality.judge_quality(docs, quality.fit_quality(docs, marks)).collect()
        assert len(rows) == 6 and all(0 <= r["score"] <= 1 for r in rows)
    kept = quality.drop_poor(docs, labels)
    assert kept.columns == docs.columns
    assert quality.drop_poor(docs.limit(0), labels).count() == 0


def test_archives(spark, tmp_path):
    big, other = "<p>" + "x" * 300, "<p>" + "é" * 60
    rows = [(5, "http://b.org/x", big), (2, "https://a.org/?q=1", big), (9, None, big), (3, "http://a.org/", "small"), (4, "http://a.org/", "small"), (6, "not a url", None), (7, "http://a.org/\r\nX: y", other), (8, "http://A.org:80/", ""), (None, "http://n.org", big), (2, "https://a.org/?q=1", big), (10, "http://[bad", other)]
    pages = spark.createDataFrame([(*r, "d") for r in rows], "page_id long, url string, html string, digest string").repartition(3)
    index = warc.write_archives(pages, block_lines=2)
    got = sorted(((r["page_id"], r["payload_bytes"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in index.read_all().collect()), key=str)
    want = []
    for page, _, html in rows:
        data = (html or "").encode()
        first = min((p for p, _, h in rows if h == html and p is not None), default=None)
        revisit = len(data) >= 100 and page is not None and page != first
        want.append((page, len(data), hashlib.sha256(data).hexdigest(), "revisit" if revisit else "response", first if revisit else None))
    assert got == sorted(want, key=str)
    found = index.lookup("http://a.org/")
    assert sorted(e["page"] for e, *_ in found) == [3, 4, 8]
    assert {payload for *_, payload in found} == {b"small", b""}
    assert index.lookup("http://zzz.org/") == [] and index.lookup("http://0.org/") == []
    assert warc.write_archives(pages.limit(0)).read_all().count() == 0


def test_url_keys():
    assert warc.url_key("https://Blog.Example.org:443/a?b=1#c") == "org,example,blog)/a?b=1"
    assert warc.url_key("http://x.org:8080") == "org,x:8080)/"


@pytest.mark.parametrize("spread", [2, 64])
def test_search_equals_brute_force(spark, spread):
    rng = np.random.default_rng(spread)
    centres = rng.integers(0, 1 << 63, 4, dtype=np.uint64)
    codes = []
    for i in range(400):
        c = int(centres[i % 4])
        for b in rng.integers(0, 64, rng.integers(0, spread)):
            c ^= 1 << int(b)
        codes.append(c if i % 3 else int(centres[0]))
    rows = [(i, [int(np.uint64(c).view(np.int64))], "x") for i, c in enumerate(codes)] + [(1000, None, "x"), (None, [5], "x")]
    frame = spark.createDataFrame(rows, "vec_id long, code array<long>, distance string")
    got = {}
    for r in hamming_search.nearest(frame, frame.filter("vec_id % 20 = 0"), 7, 1, block=64, group=8).collect():
        got.setdefault(r["vec_id"], {})[r["rank"]] = (r["distance"], r["neighbor_id"])
    for q in range(0, 400, 20):
        best = sorted(((codes[q] ^ c).bit_count(), i) for i, c in enumerate(codes) if i != q)[:7]
        assert [got[q][k] for k in range(1, 8)] == best
    assert 1000 not in got
    assert hamming_search.nearest(frame.limit(0), frame, 7, 1).count() == 0
    assert hamming_search.nearest(frame.limit(3), frame.limit(1), 7, 1).count() == 2


def test_rendering():
    html = "<title>t</title><p>One<p>Two <b>x</b>\n y<ul><li>a<li>b<ol start=3><li>c<li>d</ol><li>e</ul><table><tr><th>Name<th>N<tr><td>ab<td>1</table>end<div style='display:none'>no</div><pre>\n a\n  b</pre><script>x<y</script>&amp; < 3"
    assert html_text.html_text(html) == "One\n\nTwo x y\n\n- a\n- b\n  3. c\n  4. d\n- e\n\nName  N\nab    1\n\nend\n\n a\n  b\n\n& < 3"


def test_rendering_keeps_what_implied_tags_and_table_parts_show():
    pages = {
        "<head><title>t</title><p>text": "text",
        "<head><title>t</title>bare text": "bare text",
        "<head><noscript><img alt=no></noscript><template><p>no</template><p>x": "x",
        "<table><tr><form><td>a<td>b</form></tr></table>": "a  b",
        "<table><form><tr><td>a<td>b</form><tr><td>ccc</table>": "a    b\nccc",
        "<table><tr>loose<td>a<tr><td>b</table>": "loose\na\nb",
        "<p>f <math><mi>x</mi><mo>=</mo><mn>2</mn></math> <svg><title>no</title><text>y</text><text>z</text></svg>": "f x=2 y z",
        "a<input type=submit value='Send now'><input type=submit><input type=hidden value=no><input type=password value=no>b": "a Send now Submit b",
    }
    assert {h: html_text.html_text(h) for h in pages} == pages


def test_rendering_odd(spark):
    rng = random.Random(6)
    tags = ["<p>", "</p>", "<li>", "<ul>", "</ul>", "<td>", "<tr>", "<table>", "</table>", "<br>", "<!--", "-->", "<script>", "</script>", "<", ">", "&lt;", "<div hidden>", "</div>", "<ol start='x'>", "word ", "\n", "<pre>", "</pre>", "<a href='", "<td colspan=0>", "<details>", "<summary>"]
    pages = ["".join(rng.choice(tags) for _ in range(rng.randrange(1, 60))) for _ in range(400)] + [None, "", "<div>" * 3000 + "deep", "<ul><li>" * 300 + "x", "a" * 300_000]
    frame = spark.createDataFrame([(i, h, "y") for i, h in enumerate(pages)], "page_id long, html string, text string")
    rows = {r["page_id"]: r["text"] for r in html_text.extract(frame).collect()}
    assert rows[400] == "" and rows[401] == "" and rows[402] == "deep" and rows[404] == "a" * 300_000
    assert all("<script>" not in t for i, t in rows.items() if i < 400)
    assert html_text.extract(frame.limit(0)).count() == 0


def test_rendering_over_rows_and_sheets():
    h = html_text.html_text
    assert h("<table><tr><td rowspan=2>a<td>b<tr><td>c</table>") == "a  b\n   c"
    assert h("<table><tr><td colspan=2>wide<td rowspan=0>r<tr><td>1<td>22<tr><td>333<td>4</table>") == "wide     r\n1    22\n333  4"
    assert h('<div style="visibility:hidden">x<span style="visibility:visible">y</span></div>z') == "y\nz"
    assert h('<style>.a{display:none} p.b, #c {visibility:hidden}</style><p class=a>1<p class="b">2<p id=c>3<p>4<div class="x a">5</div>') == "4"
    assert h("<style>@media print{.z{display:none}} .q{display:none}</style><i class=z>k</i><i class=q>l</i>") == "k"
    deep = "<div>" * 400 + "<p hidden>no<b>no</b></p>yes" + "</div>" * 400
    assert h(deep + "<p>end").split() == ["yes", "end"]
    assert h("<ul><li>a<li hidden>b<li style='visibility:hidden'>c<li>d</ul>") == "- a\n- d"


def plain(node):
    """A second renderer for trees of div, p, b and ul/li: (tag, children) or text, by recursion on lists of lines."""
    lines, last = [], None

    def put(line, gap):
        nonlocal last
        if lines and (gap or last):
            lines.append("")
        lines.append(line)
        last = False

    gap = False
    held = ""

    def end():
        nonlocal held, gap
        text = " ".join(held.split())
        held = ""
        if text:
            put(text, gap)
            gap = False

    def walk(n):
        nonlocal held, gap
        if isinstance(n, str):
            held += n
            return
        tag, kids = n
        if tag != "b":
            end()
            gap = gap or tag == "p"
        for k in kids:
            walk(k)
        if tag != "b":
            end()
            gap = gap or tag == "p"

    walk(node)
    end()
    return "\n".join(lines)


def test_rendering_against_a_second_renderer():
    rng = random.Random(21)

    def tree(depth, tags):
        tag = rng.choice(tags)
        kids = [tree(depth - 1, ("b",) if tag in ("p", "b") else ("div", "p", "b")) if depth and rng.random() < 0.5 else rng.choice(("word ", " two words", "x", "  spaced  out ")) for _ in range(rng.randrange(1, 4))]
        return tag, kids

    def markup(n):
        return n if isinstance(n, str) else f"<{n[0]}>{''.join(map(markup, n[1]))}</{n[0]}>"

    for _ in range(300):
        t = tree(4, ("div",))
        assert html_text.html_text(markup(t)) == plain(t)


def test_scores_against_one_text_at_a_time(spark):
    """Batched scoring equals a plain sum over one text's features."""
    texts = [r[0] for r in spark.read.parquet(f"{SF}/documents.parquet").filter("text is not null").orderBy("doc_id").limit(60).select("text").collect()] + ["", "a", "one two", "word " * 30]
    raw = [t.encode() for t in texts]
    model = quality.SubwordModel.fit(raw, np.arange(len(raw)) % 2, 0.5, epochs=1)
    alone = []
    for t in raw:
        _, _, words, pairs, _, grams, _ = next(quality.features([t]))
        slots = np.concatenate((words, quality.AT_GRAMS + grams[grams > 0], quality.AT_PAIRS + pairs[pairs > 0])).astype(int)
        z = (model.table[slots].sum(axis=0, dtype=np.float64) / len(slots) if len(slots) else np.zeros(2)) + model.offset
        alone.append(np.exp(z[1]) / np.exp(z).sum())
    assert np.allclose(model.score(raw), alone, atol=1e-5)
    codes = language_id.OutputCodes.fit(texts, [("a", "b", "c")[i % 3] for i in range(len(texts))])
    pred, score, _ = codes.predict(texts)
    for i, t in enumerate(texts):
        one, p, _ = codes.predict([t])
        assert one[0] == pred[i] and abs(p[0] - score[i]) < 1e-9
        if one[0] != "und":
            slots = [x for x in language_id.trigram_slots(language_id.letters(t) + b"    ", language_id.BUCKETS) if x]
            z = codes.weights[slots].sum(axis=0, dtype=np.float64) / max(1, len(slots)) * codes.scale + codes.offset
            loss = [(np.log1p(np.exp(-z * c)) * codes.trust).sum() for c in codes.code]
            assert codes.langs[int(np.argmin(loss))] == one[0]


def test_every_language_is_learned(spark):
    rows = [(1000 * k + i, f"{chr(97 + k % 26)}{chr(97 + k // 26)} " * 8, f"l{k:03d}") for k in range(230) for i in range(6)]
    model = language_id.fit_languages(spark.createDataFrame(rows, "doc_id long, text string, lang string"), train_rows=500)
    assert len(model.langs) == 230


def test_search_with_repeated_ids_and_few_rows(spark):
    rng = random.Random(4)
    kind = "vec_id long, code array<long>"
    codes = [(i // 2, [rng.getrandbits(63)]) for i in range(40)]
    rows = spark.createDataFrame(codes, kind)
    got = {(r["vec_id"], r["rank"]): (r["neighbor_id"], r["distance"]) for r in hamming_search.nearest(rows.dropDuplicates(["vec_id"]), rows.dropDuplicates(["vec_id"]).filter("vec_id < 3"), 30, 1).collect()}
    one = {r["vec_id"]: r["code"][0] for r in rows.dropDuplicates(["vec_id"]).collect()}
    for q in range(3):
        want = sorted((bin(one[q] ^ c).count("1"), i) for i, c in one.items() if i != q)[:30]
        assert [got[q, k + 1] for k in range(len(want))] == [(i, d) for d, i in want]
    doubled = hamming_search.nearest(rows, rows.filter("vec_id = 1"), 5, 1).collect()
    assert len({(r["neighbor_id"], r["distance"]) for r in doubled}) >= 4 and all(r["neighbor_id"] != 1 for r in doubled)


def test_huge_page(spark, tmp_path):
    big = "<p>" + "long text " * 900_000
    pages = spark.createDataFrame([(1, "http://a.example/x", big), (2, "http://a.example/y", big), (3, None, None)], "page_id long, url string, html string")
    index = warc.write_archives(pages, f"file://{tmp_path}/w")
    told = {r["page_id"]: (r["payload_bytes"], r["record_type"], r["refers_to"], r["payload_digest"]) for r in index.read_all().collect()}
    digest = hashlib.sha256(big.encode()).hexdigest()
    assert told[1] == (len(big), "response", None, digest) and told[2] == (len(big), "revisit", 1, digest) and told[3][:3] == (0, "response", None)
