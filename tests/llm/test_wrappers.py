import functools
import html
import json
import re
import time

from deltaring.llm import wrappers as wr


def expected(page):
    """Main text of the given pages, whose main part is one article of h1 and p elements."""
    m = re.search(r"<article>(.*?)(?:</article>|$)", page, re.S)
    parts = re.split(r"</?(?:p|h1)>", m[1]) if m else []
    out = [" ".join(html.unescape(re.sub(r"<[^>]*(?:>|$)", lambda k: "\n" if k[0].startswith("<br") else "", x)).split()) for x in parts]
    return "\n\n".join(x for x in out if x)


def text_of(page):
    with wr.deep_trees():
        root = wr.parsed(page)
        return wr.main_text(root, wr.content_slots(wr.wrapper_of(root)))


def test_whole_table(spark):
    pages = spark.read.parquet("/root/testdata/sf0.001/pages.parquet")
    want = {r.page_id: expected(r.html) for r in pages.collect()}
    rows = wr.extracted_pages(pages).collect()
    assert {r.page_id: r.text for r in rows} == want and all(r.n_chars == len(r.text) for r in rows)
    shuffled = wr.extracted_pages(pages, broadcast_bytes=0).collect()
    assert {r.page_id: r.text for r in shuffled} == want


def test_wrapper_inference():
    a = wr.wrapper_of(wr.parsed("<body><ul><li>1<li>2<li>3</ul><p>x<p>y</body>"))
    b = wr.wrapper_of(wr.parsed("<body><ul><li>1</ul><div class='ad'>z</div><p>x</body>"))
    assert wr.expression(a) == "<html><ul>(<li>#</>)+</> (<p>#</>)+</>"
    assert wr.expression(wr.aligned(a, b)) == "<html><ul>(<li>#</>)+</> (<div.ad>#</>)? (<p>#</>)+</>"
    c = wr.wrapper_of(wr.parsed("<dl><dt>a<dd>b<dt>c<dd>d<dt>e<dd>f</dl>"))
    assert wr.expression(c) == "<html><dl>(<dt>#</> <dd>#</>)+</></>"
    assert wr.aligned(a, a) == a and wr.expression(wr.aligned(wr.aligned(a, b), b)) == wr.expression(wr.aligned(a, b))


def test_what_is_left_out():
    page = """<html><head><title>T</title><style>x</style></head><body><header>H</header><nav>N</nav><aside>A</aside>
    <main><h1>One &lt;two&gt;</h1><div class="cookie-notice">C</div><p>a <b>b</b><span class="ad">no</span>\n c<p>d<br>e</p>
    <ul><li>1<li>2</ul><form>f</form><script>var s = "</p>";</script><!-- c --><section id="comments-7"><p>no</p></section></main><footer>F</footer></body>"""
    assert text_of(page) == "One <two>\n\na b c\n\nd e\n\n1\n\n2"
    assert text_of("<body><div class='menu'>m</div><div><p>x &amp; y</p></div><footer>f</footer>") == "x & y"
    assert text_of("<article><p>cut &am") == "cut &am" and text_of("<article><p>a</p><p cla") == "a"
    assert text_of(None) == text_of("") == text_of("<p hidden>x</p>") == "" and text_of("plain") == "plain"


def test_odd_rows(spark):
    rows = [(1, "http://a.com/x", "<article><p>t</p></article>", 1), (1, "http://a.com/x", "<article><p>t</p></article>", 1), (2, None, None, None), (3, "::bad", "", 2), (None, "http://a.com/y", "<nav>n</nav><article>u</article>", 3), (4, "http://[x", "<p>v", 4), (5, "http://b.com", "<p>" * 3000 + "deep" + "<b>" * 300, 5)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, host int")
    got = wr.extracted_pages(df).collect()
    assert len(got) == 7 and sorted(r.text for r in got) == ["", "", "deep", "t", "t", "u", "v"]
    assert wr.extracted_pages(df.limit(0)).count() == 0
    assert wr.extracted_pages(df, 0).count() == 7


def texts_of(*pages):
    """Texts of the pages of one host."""
    roots = [wr.parsed(p) for p in pages]
    whole = functools.reduce(wr.aligned, map(wr.wrapper_of, roots))
    return [wr.main_text(r, wr.content_slots(whole)) for r in roots]


def test_templates_of_one_host_are_read_each(spark):
    one, two = "<nav>n</nav><div>x</div><article><p>a</p></article>", "<nav>n</nav><div class=content><p>b</p></div>"
    assert texts_of(one, two) == ["a", "b"] and texts_of(two, one) == ["b", "a"]
    df = spark.createDataFrame([(1, None, one), (2, "::bad", two), (3, "http://a.com/1", two), (4, "http://a.com/2", one)], "page_id long, url string, html string")
    for size in (32 << 20, 0):
        assert [r.text for r in wr.extracted_pages(df, size).orderBy("page_id").collect()] == ["a", "b", "b", "a"]


def test_embedded_elements_end_where_they_end():
    for x in ("<video-js id=v></video-js>", "<audio-player></audio-player>", "<select-box></select-box>", "<svg-icon></svg-icon>", "<svg viewBox='0 0 1 1'/>", "<svg><path d='M0'/><circle r=1></svg>", "<svg><title>t</title><text>no</text></svg>", "<svg><path/>", "<math/>", "<video src=v />", "<object data=o></object>", "<select><option>1<option>2</select>", "<canvas></canvas>", "<template><p>no</p></template>"):
        assert text_of(f"<article><p>a</p>{x}<p>b</p></article>") == "a\n\nb", x
        assert text_of(f"<article><div>{x}</div><p>b</p></article>") == "b", x
    assert text_of("<article><p>a <svg class=i><path/></svg>b <svg/>c</p></article>") == "a b c"
    assert text_of("<article><p>so <math><mi>x</mi><mo>=</mo><mn>2</mn></math> holds</p><object><p>in place</p></object><title-bar>T</title-bar></article>") == "so x=2 holds\n\nin place\n\nT"
    assert text_of("<article><script-x>a</script-x><script>no</script><p>b") == "a\n\nb"
    assert text_of("<article>" + "<svg><path/><g/></svg>" * 3000 + "<svg>" * 2000 + "<p>b") == "b"


def test_main_parts_below_noise_are_read():
    main, rest = "<article><p>a</p></article>", "<div>r</div>"
    for x in ("<div class='layout has-sidebar'>{}</div>", "<div class=page-header-fixed>{}</div>", "<div class=with-menu>{}</div>", "<form action=x>{}</form>", "<div class=sidebar-left>{}</div>", "<dialog><div class=banner>{}</div></dialog>", "<header>{}</header>"):
        assert text_of(x.format(main) + rest) == text_of(x.format("<div itemprop=articleBody><p>a</p></div>") + rest) == "a", x
    assert text_of("<div class='no-sidebar'><p>b</p></div>") == text_of("<form><p>b</p></form>") == text_of("<main><form><p>b</p></form></main>") == "b"
    assert text_of(f"<div><p>b</p></div><section id=comments>{main}</section><aside>{main}</aside>") == "b"
    assert text_of(f"<main><p>b</p><form>{main}</form><form>f</form><div class=related>{main}</div></main>") == "b\n\na"
    assert text_of("<p>x <span itemprop=articleBody>b</span>") == "b" and text_of(f"<div hidden>{main}</div>") == ""


def test_all_words_tell_the_role_of_an_element():
    many = " ".join(f"a-{c}" for c in "bcdefghijklmnop")
    for x in ("role=navigation", "role=complementary", "id=widget", "class='{} sidebar'", "class='{} share'", "class=userComments", "class=relatedPosts", "id=siteFooter", "class=cookieBanner", "class=HTMLMenu"):
        noise = x.format(many) if "{}" in x else f"class='{many}' {x}" if x[0] != "c" else x
        assert text_of(f"<article><p>a</p><div {noise}>no</div></article>") == "a", x
    assert text_of(f"<div class='{many}' itemprop=articleBody><p>a</p></div><div>r</div>") == "a"
    assert texts_of(f"<div class='{many} x' role=navigation>n</div><p>a</p>", f"<div class='{many} x'>b</div>") == ["a", "b"]


def test_what_pages_of_a_host_share_is_template():
    page = "<h1>The site</h1><div class=m><ul><li>Home<li>Help</ul></div><div class=t><p>{0}</p><p>{0} more</p></div><div class=c3>All rights <b>reserved</b></div>"
    pages = [page.format(x) for x in "abc"]
    assert texts_of(*pages) == ["a\n\na more", "b\n\nb more", "c\n\nc more"]
    some = [*pages, "<article><p>d</p></article>", "<div class=x>e</div>"]
    assert texts_of(*some)[2:] == texts_of(*some[::-1])[2::-1] == ["c\n\nc more", "d", "e"]
    whole = ["The site", "Home", "Help", "a", "a more", "All rights reserved"]
    assert texts_of(*pages[:1] * 5)[0] == texts_of(*pages[:2])[0] == "\n\n".join(whole)  # copies are one page, two are too few
    assert texts_of(*(f"<article><p>{x}</p><p>same</p></article>" for x in "abc"))[0] == "a\n\nsame"


def test_deep_and_broken_pages_return():
    """Time and depth are bounded whatever is nested or left open, and no text is lost by depth."""
    began = time.perf_counter()
    assert text_of("<article>" + "<div>" * 100_000 + "deep" + "</div>" * 100_000 + "<p>after</article>") == "deep\n\nafter"
    assert text_of("<div>x" * 50_000 + "y") == "\n\n".join(["x"] * 49_999 + ["xy"])
    assert text_of("<p>" + "<span>a" * 100_000) == "a" * 100_000
    assert text_of("<div class=sidebar>" * 3000 + "no" + "</div>" * 3000 + "<p>t") == "t"
    assert text_of("<div>" * 3000 + "<div class=sidebar><div>no</div></div><p>t") == "t"
    assert text_of("<p>start</p>" + "<a b=\"x'>" * 100_000 + "end") == "start\n\nend"
    assert text_of("<p>s</p>" + "<a '\">" * 150_000) == "s"
    assert text_of("<a \"" * 250_000) == "" and text_of("<" * 1_000_000) == "<" * 1_000_000
    assert text_of("<li><ul>" + "<blockquote>" * 30_000 + "<li></li>" * 30_000 + "z") == "z"
    assert text_of("<i><div>" + "<b>" * 50_000 + "</i>" * 50_000 + "z") == "z"
    assert text_of("<div>" * 30_000 + "</foo></p>" * 30_000 + "z") == "z"
    assert time.perf_counter() - began < 120


def test_long_lists_align():
    name = lambda i: "x-" + "".join(chr(97 + i // 26**k % 26) for k in range(3))
    page = lambda places: "".join(f"<{name(i)}>1</{name(i)}>" for i in places)
    a, b = (wr.wrapper_of(wr.parsed(page(r))) for r in (range(3000), range(0, 6000, 2)))
    assert len(wr.aligned(a, b)[1]) == 4500 and sum(not c[2] for c in wr.aligned(a, b)[1]) == 1500
    for x, y in (("abcab", "bcaab"), ("", "ab"), ("abc", "abc"), ("xay", "bac")):
        pairs = wr.matching(list(x), list(y))
        assert all(x[i] == y[j] for i, j in pairs) and pairs == sorted(pairs) and len({i for i, _ in pairs}) == len(pairs)
    assert len(wr.matching(list("abcab"), list("bcaab"))) == 4


def test_what_every_page_shows_in_its_main_part_is_template(spark):
    """The wrapper of the host decides: each page alone keeps the call to subscribe."""
    page = "<article><h1>{0}</h1><p>{0} one</p><p>two {0}</p><div class=c3>Subscribe <b>today</b></div></article><div>rest</div>"
    pages = [page.format(f"t{i}") for i in range(wr.MAIN_PAGES)]
    assert text_of(pages[0]) == "t0\n\nt0 one\n\ntwo t0\n\nSubscribe today"
    assert texts_of(*pages) == [f"t{i}\n\nt{i} one\n\ntwo t{i}" for i in range(wr.MAIN_PAGES)]
    assert texts_of(*pages[:-1])[0].endswith("today")  # too few pages to tell
    assert texts_of(*pages, "<article><div class=c3>own words</div></article>")[-1] == "own words"
    assert texts_of(*(["<article><div>all the same</div></article>"] * 9))[0] == "all the same"
    df = spark.createDataFrame([(i, f"http://a.com/{i}", p) for i, p in enumerate(pages)], "page_id long, url string, html string").repartition(4)
    assert [r.text for r in wr.extracted_pages(df).orderBy("page_id").collect()] == texts_of(*pages)
    small = wr.wrappers(df, flush_chars=10).collect()
    assert len(small) == 1 and json.loads(small[0].wrapper) == json.loads(wr.wrappers(df).first().wrapper)


def test_columns_with_clashing_names(spark):
    df = spark.createDataFrame([("<p>a", 1, "http://x.com", "w", "p", 3)], "html string, page_id long, url string, wrapper string, host string, part int")
    for size in (32 << 20, 0):
        assert [tuple(r) for r in wr.extracted_pages(df, size).collect()] == [(1, "http://x.com", "a", 1)]
