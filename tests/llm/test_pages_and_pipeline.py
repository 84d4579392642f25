"""Pages and the whole pipeline."""

from __future__ import annotations

import pytest

from trajdist.llm import decontamination, language_id, near_dup, page_template, pieces, quality
from trajdist.llm.shared import remainder, shared_folder, table

PAGE = """<!DOCTYPE html><html><head><title>T &amp; t</title><style>p{}</style><script>var a="</p><p>no</p>";</script></head><body class="home">
<header><p>Site name</p></header><nav><ul><li><a href="/">Home</a></ul></nav><!-- <p>no</p> --><div class="ad">Buy now</div>
<article><header><h1>A  title&nbsp;here</h1></header><p>First &lt;b&gt; <b>para</b>graph<br>goes
 on<p>Second &#233;<ul><li>one<li>two</ul><aside>no</aside><form><p>no</p></form><div class="user-comments"><p>reader</p></div><table><tr><td>cell<td>next</table>last <img src="x>y.png"> words</article>
<div id="cookie-notice">We use cookies</div><footer>&copy; all</footer></body></html>"""


def test_page():
    want = ["A title here", "First <b> paragraph goes on", "Second é", "one", "two", "cell", "next", "last words"]
    assert page_template.main_text(PAGE) == "\n".join(want)


@pytest.mark.parametrize("source,want", [(None, ""), ("", ""), ("just text", "just text"), ("<p>cut <b>of", "cut of"), ("<article><p>a</p><p", "a"), ("<p>1 < 2 & 3</p>", "1 < 2 & 3"), ("</div></p>x<br/>y", "x y"), ("<script>never closed", ""), ("<article>a<![CDATA[<b>]]></article>", "a<b>")])
def test_odd_pages(source, want):
    assert page_template.main_text(source) == want


def pages(spark, rows):
    return spark.createDataFrame([(*r, "clash", 1) for r in rows], "page_id long, url string, html string, host string, token long")


def test_template_of_a_host(spark):
    """Without article elements: repeated texts and link lists go, the slot that varies stays."""
    body = lambda i: f"<div class=top><p>Our site</p></div><div class=links><p><a href=/a>link {i} to somewhere else on this site</a></p></div><div class=story><p>{' '.join(f'word{i * 50 + k}' for k in range(30))}</p></div><div class=end><p>Printed daily</p></div>"
    rows = [(i, f"http://a.example/{i}", body(i)) for i in range(8)] + [(20, None, None), (21, "http://b.example/", "<p>alone</p>"), (21, "http://b.example/", "<p>alone</p>")]
    got = sorted((r.page_id, r.text, r.n_chars) for r in page_template.extract(pages(spark, rows)).collect())
    story = lambda i: " ".join(f"word{i * 50 + k}" for k in range(30))
    want = [(i, story(i), len(story(i))) for i in range(8)] + [(20, "", 0), (21, "alone", 5), (21, "alone", 5)]
    assert got == sorted(want)
    assert page_template.extract(pages(spark, [])).count() == 0


def prose(i, n=30):
    return " ".join(f"word{i * 50 + k}" for k in range(n))


def extracted(spark, bodies):
    rows = [(i, f"http://a.example/{i}", f"<html><body>{x}</body></html>") for i, x in enumerate(bodies)]
    return {r.page_id: r.text for r in page_template.extract(pages(spark, rows)).collect()}


def test_template_decides_over_article_elements(spark):
    """A teaser in an article element, the same text again and again: the slot that varies and is long is the article."""
    body = lambda i: f"<article><p>Read this first</p></article><div class=story><h2>Title {i}</h2><p>{prose(i)}</p>{f'<p>{prose(i + 100)}</p>' * (i % 3)}</div>"
    got = extracted(spark, [body(i) for i in range(6)])
    assert got == {i: "\n".join([f"Title {i}", prose(i), *[prose(i + 100)] * (i % 3)]) for i in range(6)}


def test_classes_are_ordered(spark):
    """Tokens with equal vectors whose order changes are no template."""
    mixed = lambda i: "".join(["<p>One of two</p>", "<p>Two of two</p>"][:: 1 if i % 2 else -1])
    rows = [(i, f"http://a.example/{i}", f"<html><body><div><p>{prose(i)}</p></div><section>{mixed(i)}</section></body></html>") for i in range(6)]
    (found,) = page_template.templates(pages(spark, rows)).collect()
    assert not found.dropped and found.tags
    rows = [(i, f"http://a.example/{i}", f"<html><body><div><p>{prose(i)}</p></div><section>{mixed(0)}</section></body></html>") for i in range(6)]
    (found,) = page_template.templates(pages(spark, rows)).collect()
    assert len(found.dropped) == 2


def test_whole_region_is_kept(spark):
    """Short titles, and lists and quotes of few pages, belong to the article."""
    more = lambda i: "<ul><li>item</li></ul><blockquote>quote</blockquote>" if i == 2 else ""
    got = extracted(spark, [f"<div class=top><p>Our site</p></div><div class=story><h1>Title {i}</h1><p>{prose(i)}</p>{more(i)}<p>The end</p></div><div class=end><p>Printed daily</p></div>" for i in range(6)])
    assert got == {i: "\n".join([f"Title {i}", prose(i), *(["item", "quote"] if i == 2 else []), "The end"]) for i in range(6)}


def test_copies_count_once(spark):
    """Copies of an article on half of a host's pages are not its template."""
    body = lambda i: f"<div><p>Our site</p><p>Printed daily</p></div><p>{prose(i)}</p><p>{prose(i + 100)}</p>"
    got = extracted(spark, [body(i if i < 4 else 9) for i in range(9)])
    assert got == {i: f"{prose(j)}\n{prose(j + 100)}" for i in range(9) for j in [i if i < 4 else 9]}


def test_given_pages(spark, sf_dir):
    d = table(spark, sf_dir, "pages")
    got = {r.page_id: r for r in page_template.extract(d).collect()}
    assert len(got) == d.count()
    for r in d.collect():
        text = got[r.page_id].text
        assert got[r.page_id].url == r.url and text and "<" not in text.replace("<", "", 0)[:1] and "track(" not in text


def test_pipeline(spark, sf_dir):
    """Each stage against a plain loop over what the one before has kept."""
    import corpus_pipeline

    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "quality", "near_duplicates", "decontamination", "pieces"]
    docs = table(spark, sf_dir, "documents")
    columns = docs.columns
    model = language_id.fit(docs, remainder(docs["doc_id"], 4) != 2)
    classify, coder = language_id.Classifier(model), quality.zstandard.ZstdCompressor(level=quality.LEVEL, write_checksum=False, write_content_size=False)
    from tests.llm.test_text_operators import base_measures, groups_of, hits

    left = [(r.doc_id, r.text) for r in docs.collect()]
    kept = [x for x in left if not classify(x[1])[2]]
    kept = [x for x in kept if not base_measures(x[1])[-1] and quality.bands(x[1], coder).passed]
    found = groups_of(kept)
    kept = [x for x in kept if found[x[0]][1] == x[0]]
    tests = [(str(r.item_id), r.text) for r in table(spark, sf_dir, "benchmark").collect()]
    kept = [x for x in kept if not (h := hits(x[1], tests))[1] or 20 * h[1] < h[0]]
    rows = docs
    for _, stage in corpus_pipeline.STAGES[:-1]:
        rows = stage(spark, rows, sf_dir)
        assert rows.columns == columns
        rows.write.parquet(path := shared_folder(spark, "stage"))
        rows = spark.read.parquet(path)
    assert sorted(r.doc_id for r in rows.select("doc_id").collect()) == sorted(i for i, _ in kept) and len(kept) > 50
    out = corpus_pipeline.run(spark, sf_dir).collect()
    codec = pieces.codec(corpus_pipeline.public_tokenizers.path("piece_bpe_32k.model"))
    assert {r.doc_id: r.n_tokens for r in out} == {i: len(codec.encode([t])[0]) for i, t in kept}


def test_pipeline_on_nothing(spark, sf_dir, tmp_path):
    import corpus_pipeline

    table(spark, sf_dir, "documents").limit(0).write.parquet(f"file://{tmp_path}/documents.parquet")
    table(spark, sf_dir, "benchmark").write.parquet(f"file://{tmp_path}/benchmark.parquet")
    assert corpus_pipeline.run(spark, f"file://{tmp_path}").count() == 0


def test_names_stay_apart():
    assert decontamination and near_dup
