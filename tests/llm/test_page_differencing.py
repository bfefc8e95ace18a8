"""Pages that name their article are differenced too, and structure checks what differencing finds."""

import pytest

from prunedknn.llm import html_diff

PAGE = (
    "<nav>Home</nav><div>Latest news</div>{}<div>Only on {}</div><article><p>{}</p><p>shared passage</p></article>"
    "<article><h2>Box</h2><p>of the site</p></article><footer>All rights</footer>"
)


@pytest.mark.parametrize("block", [2, 256])
def test_every_page_is_differenced(spark, monkeypatch, block):
    monkeypatch.setattr(html_diff, "BLOCK", block)
    rows = [(i, f"http://h.org/{i}", PAGE.format("", i, f"story {i}")) for i in range(5)]
    rows += [(5, "http://h.org/5", "<article><p>story 5</p><p>shared passage</p></article>")]  # its article stands alone
    rows += [(6, "http://alone.org/", PAGE.format("", 6, "story 6"))]  # nothing tells the box from an article
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    out = {r["page_id"]: r for r in html_diff.main_text(pages).collect()}
    assert len(out) == len(rows)
    for i in range(5):
        assert out[i]["text"] == f"story {i}\n\nshared passage"
        # outside "Latest news"; inside the passage, which is given back, and two lines of the box
        assert (out[i]["n_repeated"], out[i]["n_restored"]) == (4, 1)
    assert out[5]["text"] == "story 5\n\nshared passage" and (out[5]["n_repeated"], out[5]["n_restored"]) == (1, 1)
    assert out[6]["text"] == "story 6\n\nshared passage\n\nBox\n\nof the site" and out[6]["n_repeated"] == 0


def test_copies_of_a_story_beside_other_boxes_keep_it(spark):
    page = "<article><p>same story</p></article><article><p>box {}</p></article>"
    pages = spark.createDataFrame([(i, f"http://h.org/{i}", page.format(i)) for i in range(3)], "page_id long, url string, html string")
    assert {r["text"] for r in html_diff.main_text(pages).collect()} == {f"same story\n\nbox {i}" for i in range(3)}


def test_marked_lines_of_a_page_are_differenced(spark):
    page = "<nav>Home</nav><article><p>story {0}</p></article><footer>Page {0}</footer>"
    pages = spark.createDataFrame([(i, f"http://h.org/{i}", page.format(i)) for i in range(3)], "page_id long, url string, html string")
    out = html_diff.main_text(pages).collect()
    assert {(r["text"], r["n_repeated"], r["n_restored"]) for r in out} == {(f"story {i}", 1, 0) for i in range(3)}
