"""Page differencing against a plain version, and malformed or odd pages."""

import random
import time

import pytest

from fewrounds.llm import html as h


def plain(rows):
    """main text of (page_id, url, html) rows: each page against the pages before and after it on its host."""
    keyed = sorted({(u.split("/")[2].lower(), "/" + "/".join(u.split("/")[3:]).split("?")[0], k, p) for k, u, p in rows if u})
    shared = {}
    for i, (host, _, k, p) in enumerate(keyed):
        own = h.judged_lines(h.blocks(p))
        seen, places = 0, set()
        for j in (i - 1, i + 1):
            if 0 <= j < len(keyed) and keyed[j][0] == host:
                other = h.judged_lines(h.blocks(keyed[j][3]))
                table = [[0] * (len(other) + 1) for _ in range(len(own) + 1)]
                for x in range(len(own) - 1, -1, -1):
                    for y in range(len(other) - 1, -1, -1):
                        table[x][y] = table[x + 1][y + 1] + 1 if own[x] == other[y] else max(table[x + 1][y], table[x][y + 1])
                common = h.aligned([hash(t) for t in own], [hash(t) for t in other])
                assert len(common) == table[0][0] and all(own[c] in other for c in common)
                if sum(len(own[c]) for c in common) <= h.COPY * sum(map(len, own)) or not own:
                    seen += 1
                    places |= common
        shared[k, p] = (places, seen > 0)
    return sorted((k, h.main_text(h.blocks(p), *(shared[k, p] if u else ((), False))) if p else "") for k, u, p in rows)


def page(r, k):
    menu = [f"<div>Menu {r.randrange(4)}</div>" for _ in range(4)]
    body = [f"<p>body {k} line {i} {r.random()}</p>" for i in range(r.randrange(6))]
    hint = "<p class='notice'>Site notice</p>" if r.random() < 0.5 else f"<p class='notice'>Own notice {k}</p>"
    whole = f"<article>{''.join(body)}{hint}</article>" if r.random() < 0.4 else "".join(body)
    return f"<html><body>{''.join(menu)}{whole}<div class='ad'>Ad {k}</div><footer>f</footer></body></html>"


def test_equals_the_plain_version(spark):
    r = random.Random(3)
    rows = [(k, f"http://host{r.choice('aab')}.org/d/{r.randrange(60)}/{k}", page(r, k)) for k in range(80)] + [(90, None, page(r, 90)), (91, "http://hosta.org/d/1", None), (92, "http://hostb.org/x", "")]
    rows += rows[:5]
    df = spark.createDataFrame([(*x, "kept") for x in rows], "page_id long, url string, html string, shared string")
    got = sorted((x.page_id, x.text) for x in h.extract(df.repartition(3)).collect())
    assert got == plain([(k, u, p or "") for k, u, p in rows])
    some = dict(got)
    assert any("Own notice" in t for t in some.values()) and not any("Ad " in t or "Menu" in t and "Menu" * 3 in t for t in some.values())
    assert h.extract(df.where("false")).count() == 0


def test_copies_and_unmarked_parts(spark):
    text = " ".join(f"word{i}" for i in range(30))
    rows = [(1, "http://a.org/p?print=1", f"<p>{text}</p>"), (2, "http://a.org/p", f"<p>{text}</p>"), (3, "http://c.org/1", f"<article><p>teaser</p></article><div>{text} one</div><div>menu</div>"), (4, "http://c.org/2", f"<article><p>other</p></article><div>{text} two</div><div>menu</div>")]
    got = {x.page_id: x.text for x in h.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == {1: text, 2: text, 3: f"teaser\n\n{text} one", 4: f"other\n\n{text} two"}


@pytest.mark.parametrize(
    ("page", "text"),
    [
        ("<p title=it's>hello</p>", "hello"), ("<p title='a>b'>x", "x"), ("<p>a < b &amp;&amp; c > d</p>", "a < b && c > d"), ("<article><p>x<!-- a > b --> y</p><script>if (a<b) '</p>'</script></article>", "x y"),
        ('<main class="content has-sidebar"><p>A</p><section><h2>Comments (3)</h2><p>c1</p></section><p>B</p></main>', "A\n\nB"), ('<div class="sidebar-wrap"><article><p class="share-price">9</p><label>L</label></article></div>', "9\n\nL"),
        ("<article>a<aside>b</aside><div hidden>c</div><form>d</form>e</article>", "a\n\ne"), ("<svg/><p>after</p>", "after"),
    ],
)
def test_pages(page, text):
    assert h.main_text(h.blocks(page)) == text


def test_long_and_broken_pages():
    began = time.time()
    for bad in ("<script " * 20000, '<p a="' * 20000, "<script>" * 20000, "<" * 300000, "<!--" * 50000, '<a b="c' * 20000, "</" * 100000, "<p " + "a=b " * 100000, "<div>" * 30000 + "</b>" * 30000 + "</div>" * 30000, "<p>" + "x " * 500000):
        h.main_text(h.blocks(bad))
    assert time.time() - began < 20
    assert h.main_text(h.blocks("<article>" + "<p>x</p>" * 20000 + "</article>")).count("x") == 20000
