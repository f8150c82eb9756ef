"""Boilerplate of raw pages goes once they are broken into the lines that they show."""

from conftest import DATA


def test_rendered(spark):
    from zonal.llm.line_dedup import rendered

    html = '<html><head><title>T</title><style>p{}</style><script>x="</p>";</script></head><body><!-- <p>no</p> --><nav><ul><li><a href="/a">Home</a></li></ul></nav><P class="q">1 &lt; 2 <b>bold</b><br>two\nthree</p><script>open'
    rows = spark.createDataFrame([(1, html), (2, None), (3, ""), (4, "plain")], "i int, html string")
    got = {r.i: r.t for r in rows.select("i", rendered(rows.html).alias("t")).collect()}
    assert got == {1: "T\nHome\n1 < 2 bold\ntwo\nthree", 2: None, 3: "", 4: "plain"}


def test_planted_boilerplate_of_a_host_goes(spark, tmp_path):
    from zonal.llm.queries import LINE_PAGES, op1_line_dedup

    page = "<html><body><nav><a href='/'>Home of the site</a></nav><style>p{{}}</style><p>own text {0}</p><footer>All rights kept</footer></body></html>"
    rows = [(i, f"http://h.example/{i}", page.format(i)) for i in range(LINE_PAGES + 3)] + [(100, "http://other.example/", page.format(100)), (101, None, None)]
    spark.createDataFrame(rows, "page_id bigint, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    got = {r.page_id: r for r in op1_line_dedup(spark, str(tmp_path)).collect()}
    assert all(got[i].kept_text == f"own text {i}" and (got[i].n_lines, got[i].n_dropped) == (3, 2) for i in range(LINE_PAGES + 3))
    assert got[100].n_dropped == 0 and got[101].kept_text is None and len(got) == len(rows)


def test_given_pages_lose_lines(spark):
    from zonal.llm.queries import QUERIES

    out = QUERIES["op1_line_dedup"](spark, f"{DATA}/sf0.1")
    n, lines, dropped = out.selectExpr("count(*)", "sum(n_lines)", "sum(n_dropped)").first()
    assert n == 2500 and lines > 5 * n and dropped > 0


def test_repeated_page_ids(spark, tmp_path):
    """Pages under one id count as pages of their own and are cleaned alike."""
    from zonal.llm.queries import op1_line_dedup

    rows = [(7, "http://h.example/x", "<p>menu of the site</p><p>own</p>")] * 3 + [(i, "http://h.example/y", f"<p>text {i}</p>") for i in range(2)]
    spark.createDataFrame(rows, "page_id bigint, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    got = sorted((r.page_id, r.n_lines, r.n_dropped, r.kept_text) for r in op1_line_dedup(spark, str(tmp_path)).collect())
    assert got == [(0, 1, 0, "text 0"), (1, 1, 0, "text 1"), (7, 2, 2, ""), (7, 2, 2, ""), (7, 2, 2, "")]
