from collections import Counter

from pyspark.sql import functions as F

from jointsem.llm.html_text import Page, host, main_texts, templates

BAR = '<div class="x7"><span>Weather</span> <b>sunny</b></div>'


def page(n, body, extra=""):
    return f'<html><head><title>T {n}</title><script>var a="</p><!-- ";</script></head><body>{BAR}<div id=q>{body}</div>{extra}<p>unique tail {n} of this page that nobody else has</p></body></html>'


def test_repeated_elements_of_a_host_go(spark):
    rows = [(i, f"http://A.example/{i}", page(i, f"<p>Text number {i} is long enough to be the main part of it.</p>")) for i in range(20)]
    rows += [(100, "http://b.example/1", page(1, "<p>Only page here.</p>")), (101, None, None), (102, "http://a.example:80/x", ""), (None, "http://a.example/", "<p>no markup")]
    rows += [rows[3]]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "'z' as host", "'z' as text", "1 as hash")
    got = main_texts(pages).collect()
    assert len(got) == len(rows)
    of = {r.page_id: r for r in got}
    assert of[3].text == "Text number 3 is long enough to be the main part of it. unique tail 3 of this page that nobody else has"
    assert of[100].text.startswith("Weather sunny Only page here.")
    assert (of[101].text, of[101].n_chars, of[102].text, of[None].text) == ("", 0, "", "no markup")
    assert all(r.n_chars == len(r.text) for r in got)
    assert main_texts(pages.where("page_id < 0")).collect() == []


def test_counts_equal_brute_force(spark):
    rows = [(i, f"http://h{i % 3}.example/", page(i, f"<p>p{i % 4}</p><p>q{i}</p>")) for i in range(60)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    want = {}
    for h in range(3):
        own = [Page(p).candidates() for _, u, p in rows if f"h{h}." in u]
        n = Counter(x for c in own for x in c)
        want[f"h{h}.example"] = sorted(x for x, k in n.items() if k >= 4 and k >= 0.05 * len(own))
    assert {r.host: sorted(r.hashes) for r in templates(pages).collect()} == want


def test_articles_of_copies_stay(spark):
    body = "<nav>menu</nav><article><h1>Same</h1><p>copy</p></article><div class=ad>buy</div>"
    pages = spark.createDataFrame([(i, f"http://c.example/{i}", body) for i in range(30)], "page_id long, url string, html string")
    assert {r.text for r in main_texts(pages).collect()} == {"Same copy"}


def test_repeated_blocks_inside_articles_go(spark):
    """Unlisted boxes that most of a host's articles hold; a copied article counts once, and no article loses most of its text."""
    box = "<div class=x7>Read our magazine today</div>"
    rows = [(i, f"http://d.example/{i}", f"<article><p>Story {i} goes on for quite a while, and so do all the others.</p>{box if i < 12 else ''}<p>The end of {i}.</p></article>") for i in range(16)]
    rows += [(100 + i, "http://e.example/", "<article><p>Copied text of some length.</p><p>Its end.</p></article>") for i in range(20)]
    rows += [(200 + i, "http://f.example/", f"<article><p>One line here of most.</p><p>Two lines here of most.</p><p>{i}</p></article>") for i in range(20)]
    of = {r.page_id: r.text for r in main_texts(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert all(of[i] == f"Story {i} goes on for quite a while, and so do all the others. The end of {i}." for i in range(16))
    assert {of[100 + i] for i in range(20)} == {"Copied text of some length. Its end."}
    assert all(of[200 + i] == f"One line here of most. Two lines here of most. {i}" for i in range(20))


def text(source):
    return Page(source).text()


def test_markup():
    assert text("<article><p>a<p><b>b<i>c</b></i>\n d&amp;&lt;&eacute;&#x27;<br>e</article><footer>f</footer>") == "a bc d&<é' e"
    assert text('<main>x<aside>s</aside><form>f</form><section class="reader comments">c</section>y<!-- z --></main>w') == "x y"
    assert text("<ul><li>a<li>b<ul><li>c</ul><li>d</ul>") == "a b c d"
    assert text("<table><tr><td>1<td>2<tr><th>3</table>") == "1 2 3"
    assert text('<p title="a>b">t</p><p class=adventure>u</p><p id="top-banner">v</p>') == "t u"
    assert text("a < b <c>d</c> & e<script>if (a<b) x='</p>'</script>") == "a < b d & e"
    assert text("<p>un<b>der</b>line</p><div>x</div>y") == "underline x y"
    assert text("<!-- open") == "" and text("") == "" and text("<") == "<"


def test_hosts(spark):
    df = spark.createDataFrame([("https://U:p@Ex.org:8080/a?b#c",), ("nonsense",), (None,), ("http://x.y",)], "url string")
    assert [r[0] for r in df.select(host()).collect()] == ["ex.org", "", "", "x.y"]
    assert df.select(F.count("*")).first()[0] == 4
