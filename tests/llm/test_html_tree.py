"""Importance decides inside and outside of article and main."""

import math
import random
from collections import Counter, defaultdict

import pytest

from wedgework.llm import htmltext

WORDS = "river stone morning light seven birds walk slowly above old houses while the wind turns".split()


def extracted(spark, pages):
    rows = [(i, f"http://t.example/{i}", p) for i, p in enumerate(pages)]
    return [r.text for r in htmltext.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).orderBy("page_id").collect()]


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


def test_boilerplate_inside_an_article_goes(spark):
    rng = random.Random(1)
    own = [prose(rng, 40) for _ in range(20)]
    got = extracted(spark, [f"<body><article><p class=lead>Read our app terms</p><div class=t>{t}</div></article></body>" for t in own])
    assert got == own


def test_main_text_beside_an_article_card_stays(spark):
    rng = random.Random(2)
    own = [prose(rng, 60) for _ in range(20)]
    page = "<body><div class=x>{}</div><ul><li><article><p>{}</p></article></li></ul></body>"
    for n in (20, 1):  # with statistics of the host, and without
        got = extracted(spark, [page.format(t, prose(rng, 5)) for t in own[:n]])
        assert all(t in g for t, g in zip(own, got, strict=False))


def test_copied_articles_stay(spark):
    rng = random.Random(3)
    text = prose(rng, 50)
    assert extracted(spark, [f"<body><main><p>{text}</p></main></body>"] * 20) == [text] * 20


def changing(rng, i):
    """A page without article, main or telling names: its menu, notice and last line change on every page."""
    menu = "".join(f"<li><a href='/{j}'>{prose(rng, 1)}{rng.randrange(99)}</a></li>" for j in range(5))
    body = "".join(f"<p>{prose(rng, rng.randrange(8, 40))}</p>" for _ in range(rng.randrange(2, 9)))
    return f"<body><div class=a><ul>{menu}</ul></div><div class=b>{prose(rng, 6)} {i}</div><div class=c><h2>Title {i}</h2>{body}</div><div class=d>(c) {i} {prose(rng, 4)}</div></body>", body


def test_changing_boilerplate_goes_by_its_layout(spark):
    rng = random.Random(4)
    pages = [changing(rng, i) for i in range(30)]
    want = [f"Title {i} " + " ".join(x.split("</p>")[0] for x in body.split("<p>")[1:]) for i, (_, body) in enumerate(pages)]
    assert extracted(spark, [p for p, _ in pages]) == want


def test_very_long_page_and_comments(spark):
    rng = random.Random(5)
    body = "".join(f"<p>{prose(rng, 30)} {i}</p>" for i in range(4000))
    page = f"<body><nav><a href=x>Home</a></nav><article>{body}<div id=comments><p>first!</p><div class='comment-7'>so true</div></div><math><mi>x</mi></math></article></body>"
    got = extracted(spark, [page])[0]
    assert got.startswith(body[3:40]) and got.endswith("x") and "first!" not in got and "so true" not in got and "Home" not in got and got.count(" 3999") == 1


def test_importance_against_brute_force(spark):
    rng = random.Random(6)
    html = [changing(rng, i)[0] if i % 3 else "<body><div class=a>same</div><p>one</p><aside>x</aside></body>" for i in range(24)]
    rows = [(i, f"//h{i % 2}.example/{i}", p) for i, p in enumerate(html)]
    got = {(r.host, r.path): r for r in htmltext.importances(htmltext.statistics(spark.createDataFrame(rows, "page_id long, url string, html string"))).collect()}
    by, seen = defaultdict(list), set()
    for _, url, p in rows:
        for path, kind, layout, text, share, link, whole in htmltext.nodes_of(htmltext.blocks(p)):
            if (key := (htmltext.host_of(url), path, layout, text, whole)) not in seen:
                seen.add(key)
                by[key[:2]].append((kind, layout, text, share, link))

    def entropy(values):
        n = len(values)
        return 1.0 if n < 2 else max(0.0, -sum(c / n * math.log(c / n) for c in Counter(values).values()) / math.log(n))

    def importance(host, path):
        shown, prior = 0.0, 0.5
        for p in htmltext.prefixes(path):
            v = by[host, p]
            content, presentation = entropy([x[2] for x in v]), entropy([x[1] for x in v])
            share, link = (sum(x[j] for x in v) / len(v) for j in (3, 4))
            shown = content * max(presentation, share, shown * (1 - link) if v[0][0] == "f" else 0.0)
            prior = {"n": -1.0, "c": 1.0}.get(v[0][0], prior)
        w = htmltext.PRIOR_PAGES / (htmltext.PRIOR_PAGES + len(by[host, path]))
        return (1 - w) * shown + w * prior

    assert set(got) == set(by)
    for key, r in got.items():
        assert r.pages == len(by[key]) and r.importance == pytest.approx(importance(*key), abs=1e-9), key
