from freshview.llm import page_text as P
from freshview.llm.common import table

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var a="</p><article>x";</script></head><body class="has-sidebar">
<header id=top><a href="/">Site &amp; name</a></header><nav><ul><li>Home<li>News</ul></nav><div class="cookie-notice">We use cookies</div>
<main><article><header><h1>Big&nbsp;title</h1></header><p>One <b>bold</b>ly &lt;put&gt; text<br>next   line<p>Second &#233; para &unknown; a < b
<div class="ad">Buy</div><aside>Side</aside><form><input>Mail</form><figure><img src="a>b" alt='x > y'><figcaption>Caption</figcaption></figure>
<ul><li>point one<li>point <i>two</i></ul><!-- hidden --><table><tr><td>c1<td>c2</table></article>
<section id="comments"><article class="comment">First!</article></section></main><div class="sidebar">Links</div><footer>&copy;</footer><script>end"""
WANT = "Big title One boldly <put> text next line Second é para &unknown; a < b Caption point one point two c1 c2"


def test_one_page():
    assert P.extract(PAGE)[0] == WANT
    for odd in ("", None, "<", "<!-- open", "<script>", "</p></div>", "<p", "a<b>c"):
        P.extract(odd)
    assert P.extract("just text")[0] == "just text" and P.extract("<p>a</p><p>b")[0] == "a b"
    assert P.extract("<div>" * 20000 + "deep" + "</div>" * 20000)[0] == "deep"


def test_letters_that_change_length():
    # a capital letter that is two letters in lower case, before elements whose end is searched for
    for n in (3, 12, 40):
        page = f"<p>{'İ' * n} start</p><script>var a = '</p>';</SCRIPT><p>after the script</p><title>no</TITLE ><p>end</p>"
        assert P.extract(page)[0] == f"{'İ' * n} start after the script end"
    assert P.extract("<p>a</p><script>b</ſcript>b</Script><p>c")[0] == "a c"


def test_ambiguous_names_inside_the_article():
    kept = ["class='share-price'", "class='alert-box'", "id='search-results'", "class='noticeBoard'", "class='social-history'"]
    gone = ["class='share'", "class='cookie-text'", "class='site-notice'", "class='related-widget wide'", "class='advert-box'", "id=comments", "class='share-buttons'", "class='newsletter-box'"]
    for left, right in (("<article>", "</article>"), ("<main>", "</main>"), ("<div id=content>", "</div>")):
        for attr in kept + gone:
            page = f"<body>{left}<p>Own text</p><div {attr}>Held words <a href=x>one</a></div><p>Last</p>{right}</body>"
            assert P.extract(page)[0] == ("Own text Held words one Last" if attr in kept else "Own text Last"), (left, attr)
        linked = f"<body>{left}<p>Own text</p><div class='related-stories'><a href=x>Some story</a> <a href=y>Other story</a></div>{right}</body>"
        assert P.extract(linked)[0] == "Own text"
    # beside the content one word is enough
    assert P.extract("<body><div class='share-price'>Box</div><p>Own text</p></body>")[0] == "Own text"


def brute_templates(pages):
    """Per host the subtree hashes found with enough distinct main texts, counted with plain sets."""
    found, texts = {}, {}
    for host, page in pages:
        hashes, content = P.hashes_and_content(page)
        texts.setdefault(host, set()).add(content)
        for h in hashes:
            found.setdefault((host, h), set()).add(content)
    out = {}
    for (host, h), c in found.items():
        if len(c) >= P.MIN_PAGES and len(c) >= P.MIN_SHARE * len(texts[host]):
            out.setdefault(host, set()).add(h)
    return out


def test_templates_against_brute_force(spark, monkeypatch):
    import random

    rng = random.Random(3)
    blocks = [f"<div>Block {k}</div>" for k in range(12)]
    pages = [(rng.choice(["hot"] * 6 + ["a", "b", ""]), f"<body>{''.join(rng.sample(blocks, 3))}<article><p>Text {rng.randrange(60)}</p></article></body>") for _ in range(300)]
    df = spark.createDataFrame(pages + [("a", None)], "host string, html string")
    want = brute_templates(pages + [("a", None)])
    assert want and {r.host: set(r.template) for r in P.site_templates(df).collect()} == want
    # with every host treated as hot
    monkeypatch.setattr(P, "hot_keys", lambda rows, key: [(h, 3) for h in ("hot", "a", "b", "")])
    assert {r.host: set(r.template) for r in P.site_templates(df).collect()} == want


def test_templates_by_host(spark):
    body = "<html><body><div class=x><p>Same bar {h}</p></div><div class=y><h1>Title {i}</h1><p>Own text {i}</p><p>Shared words</p></div><div>Tail of {h}</div></body></html>"
    rows = [(i, f"http://h{i % 2}.org/{i}", body.format(h=i % 2, i=i), "t", 0) for i in range(20)]
    rows += [(100, "https://lone.org/", body.format(h=0, i=100), "t", 0), (101, None, None, "t", 0), (102, "http://h1.org", "", "t", 0), (0, rows[0][1], rows[0][2], "t", 0)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, text string, host int")
    got = {r.page_id: r for r in P.extract_pages(df).collect()}
    assert got[3].text == "Title 3 Own text 3" and got[3].n_template == 3 and got[3].n_chars == 18
    assert got[100].text == "Same bar 0 Title 100 Own text 100 Shared words Tail of 0"
    assert got[101].text == "" and got[102].n_chars == 0
    assert P.extract_pages(df).count() == len(rows) and P.extract_pages(df.limit(0)).count() == 0


def test_copies_are_no_template(spark):
    inner = "<h1>Same title</h1><p>Same words</p><ul><li>one<li>two</ul><table><tr><td>cell</table><div>box</div><section>part</section><figure><figcaption>cap</figcaption></figure>"
    text = "Same title Same words one two cell box part cap"
    bar = "<div class=x>Bar of the site</div>"
    for k, (left, right) in enumerate([("<article>", "</article>"), ("<main>", "</main>"), ("<div id=content>", "</div>"), ("<div class=z>", "</div>")]):
        own = lambda i: f"<html><body>{bar}{left}<h1>Title {i}</h1><p>Own {i}</p>{right}</body></html>"  # noqa: E731, B023
        rows = [(i, f"http://h{k}.org/{i}", f"<html><body>{bar}{left}{inner}{right}</body></html>") for i in range(6)]
        rows += [rows[0]] * 3 + [(100 + i, f"http://h{k}.org/{i}", own(i)) for i in range(8)]
        got = P.extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
        assert len(got) == len(rows)
        for r in got:
            assert r.text == (text if r.page_id < 100 else f"Title {r.page_id - 100} Own {r.page_id - 100}") and r.n_template == 1


def test_near_copies_and_emptied_pages():
    # a list that many articles share stays; a page of nothing but template keeps its text
    page = "<div>Bar</div><article><p>Text {}</p><ul><li>one</ul><div>box</div></article>"
    template = frozenset(P.subtree_hashes(P.parse(page.format(0))).values())
    assert P.extract(page.format(1), template) == ("Text 1 one box", 1)
    only = "<div id=content><div>Alpha</div><ul><li>Beta</ul></div>"
    assert P.extract(only, frozenset(P.subtree_hashes(P.parse(only)).values()))[0] == "Alpha Beta"
    named = "<div id=content><div>Bar</div><p>Quote</p><p>Own</p></div>"
    template = frozenset(P.subtree_hashes(P.parse("<div>Bar</div><p>Quote</p>")).values())
    assert P.extract(named, template) == ("Quote Own", 1)


def test_given_pages(spark):
    import html
    import re

    pages = {r.page_id: r.html for r in table(spark, "/root/testdata/sf0.01", "pages").collect()}
    rows = P.op1_page_text(spark, "/root/testdata/sf0.01").collect()
    assert len(rows) == len(pages)
    for r in rows:
        article = re.search(r"<article>(.*?)(</article>|<footer>|\Z)", pages[r.page_id], re.S)[1]
        plain = " ".join(html.unescape(re.sub(r"</?(?:p|h1|br)>", " ", re.sub(r"</?b>", "", article))).split())
        assert r.text == plain and r.n_chars == len(plain)
