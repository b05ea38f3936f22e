"""Block labeller on unseen made-up pages and on known layouts."""

import random

from partgraph.llm import html_blocks as H


def test_unseen_pages_and_repair():
    model = H.labeller()
    rng = random.Random(99)
    right = total = 0
    for _ in range(60):
        page = H.write_page(rng)
        want = " ".join(t for _, t, _ in H.blocks_of(page) if t[0] == "q")
        right += H.main_texts(model, [page])[0] == want
        total += 1
    assert right / total >= 0.9
    page = '<html><head><title>T</title><script>var t="</p>";</script></head><body><nav><ul><li><a href="/a">Home</a></li></ul></nav><div class="ad">Buy &amp; go.</div><article><h1>One &lt;two&gt;</h1><p><b>Some  text here.<br><p>More\ntext in it.</p></article><footer>&copy; x</footer></body></html>'
    assert H.main_texts(model, [page, None, ""]) == ["One <two> Some text here. More text in it.", "", ""]


def test_query_shape(spark):
    df = spark.createDataFrame([(1, "u", None, 3), (None, None, "<article><p>Plain words in a page.</p></article>", 4)], "page_id long, url string, html string, n_chars int")
    got = {r.page_id: (r.text, r.n_chars) for r in H.extract(df).collect()}
    assert got[1] == ("", 0) and got[None][0] == "Plain words in a page."
    assert H.extract(df.limit(0)).count() == 0
