"""Page text and chat transcripts."""

from collections import Counter

import numpy as np

from certgraph.llm import chat
from certgraph.llm.html_text import extract_pages, main_text, smoothed

PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{{}}</style><script>var x="<p>no</p>";</script></head><body>
<header class="site"><h1>Site name</h1><a href="/">Home</a></header><nav><ul><li><a href="/a">One</a></li><li><a href="/b">Two</a></li></ul></nav>
<div class="cookie-notice">We use cookies.</div><!-- ad --><div class="ad">Buy now</div>
{0}
<aside class="sidebar"><p>Read also this and that</p></aside><section id="comments"><p>First!</p></section>
<form><p>Subscribe</p><input><button>Go</button></form><footer>&copy; nobody</footer></body></html>"""
BODY = "<h1>A title</h1><p>First  paragraph\nof &lt;text&gt; &amp; <b>more</b> text, long enough to be prose.<br>Next line<p>Second one with <a href='#'>a link</a> in it, and further words.</p><script>bad()</script><ul><li>Point one</li><li>Point two</li></ul>"
WANT = "A title\nFirst paragraph of <text> & more text, long enough to be prose. Next line\nSecond one with a link in it, and further words.\nPoint one\nPoint two"


def test_marked_article():
    for tag in ("article", "main", 'div role="main"'):
        name = tag.split()[0]
        assert main_text(PAGE.format(f"<{tag}>{BODY}</{name}>")) == WANT


def test_unmarked_article():
    assert main_text(PAGE.format(f'<div id="content">{BODY}</div>')) == WANT


def test_regions_decide_on_marked_pages_too():
    long = "A paragraph of plain prose that goes on for quite a while, so that it holds far more text than tags. " * 3
    prose = "".join(f"<p>{i} {long}</p>" for i in range(8))
    plain = [f"{i} {long}".strip() for i in range(8)]
    card = "<article><h3><b>Also</b></h3><p><i><b>See</b></i></p></article>"
    got = main_text(f"<body>{card}<ul><li>Tags</li><li>Up</li><li>On</li></ul><div>{prose}</div></body>").split("\n")
    assert got[-8:] == plain and not {"Also", "See"} & set(got)
    reply = "A short second piece, dense enough to count though under a quarter of the first."
    assert main_text(f"<body><article>{prose}</article><article><p>{reply}</p></article></body>").split("\n") == [*plain, reply]
    menu = "".join(f"<p><a href='/{i}'>Other story {i}</a></p>" for i in range(6))
    assert main_text(f"<body><article>{prose}{menu}</article></body>").split("\n") == plain


def test_the_ratio_decides_without_marks(monkeypatch):
    from certgraph.llm import html_text

    prose = [f"{i} " + "A paragraph of plain prose that goes on for quite a while, so that it holds far more text than tags. " * 3 for i in range(6)]
    tags = "".join(f"<li><i><b>{x}</b></i></li>" for x in ("Tags", "Up", "On", "More", "Less", "Top"))
    page = f"<body><div><h3><b>Lists</b></h3><ul>{tags}</ul></div><div><h2>Title</h2>{''.join(f'<p>{p}</p>' for p in prose)}<p>End.</p></div></body>"
    assert main_text(page).split("\n") == ["Title", *(p.strip() for p in prose), "End."]
    monkeypatch.setattr(html_text, "smoothed", lambda v: np.ones(len(v)))
    assert main_text(page).startswith("Lists\nTags")


def test_pages_without_marks_give_the_same_text(spark, sf):
    import re

    for r in spark.read.parquet(f"{sf}/pages.parquet").collect():
        plain = re.sub(r"<article\b[^>]*>", "<div>", r.html).replace("</article>", "</div>")
        assert main_text(plain) == main_text(r.html)


def test_unclosed_links_lose_nothing():
    rest = [f"Line {i} of a page without an article, long enough to be prose." for i in range(12)]
    page = "<body><div><p>Some <a href='x'>words that link.</p>" + "".join(f"<p>{x}</p>" for x in rest) + "</div></body>"
    assert main_text(page).split("\n") == ["Some words that link.", *rest]
    assert main_text(page.replace("that link.", "that</a> link.")) == main_text(page)


def test_cut_off_and_broken_pages():
    whole = PAGE.format(f"<article>{BODY}</article>")
    assert main_text(whole[: whole.index("<aside")]) == WANT
    assert main_text("<article><p>cut off &am") == "cut off &am"
    assert main_text("<p>a<div>b</p></i></div><p>c") == "a\nb\nc"
    assert main_text("<article><header><h1>T</h1></header><p>body</p><footer>by me</footer></article>") == "T\nbody"
    assert [main_text(x) for x in (None, "", " ", "<html></html>", "plain")] == ["", "", "", "", "plain"]
    assert main_text("<p>" + "word " * 200_000) == ("word " * 200_000).strip()


def test_smoothing_keeps_level_lines():
    assert np.allclose(smoothed(np.full(9, 4.0)), 4.0) and len(smoothed(np.ones(1))) == 1


def test_pages_table(spark):
    pages = spark.createDataFrame([(1, "u", PAGE.format(f"<article>{BODY}</article>"), "x"), (None, None, None, None), (1, "u", "", "x")], "page_id long, url string, html string, text string")
    got = extract_pages(pages).collect()
    assert sorted((r.page_id or 0, r.n_chars) for r in got) == [(0, 0), (1, 0), (1, len(WANT))]
    assert extract_pages(pages.limit(0)).count() == 0


def test_whole_pages_against_their_articles(spark, sf):
    import html
    import re

    pages = {r.page_id: r.html for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    for r in extract_pages(spark.read.parquet(f"{sf}/pages.parquet")).collect():
        inner = re.search(r"<article>(.*?)(</article>|$)", pages[r.page_id], re.S).group(1)
        blocks = [" ".join(html.unescape(re.sub("<[^>]*>", "", b)).split()) for b in re.split(r"</?(?:p|h1)>|<br>", inner)]
        assert r.text == "\n".join(b for b in blocks if b)


def test_roles_are_recovered(spark, sf):
    conversations = spark.read.parquet(f"{sf}/conversations.parquet")
    turns = conversations.count()
    got = chat.formatted_chats(conversations).collect()
    assert sum(r.n_turns for r in got) == turns
    assert sum(r.roles_right for r in got) >= 0.95 * turns
    exact = [r for r in got if r.roles_right == r.n_turns == r.n_found]
    texts = {}
    for r in conversations.collect():
        texts.setdefault(r.conv_id, {})[r.turn] = (r.role, r.text)
    for r in exact[:20]:
        assert r.chat == chat.render_turns([x for _, x in sorted(texts[r.conv_id].items())])


def test_held_out_transcripts_and_foreign_markers(spark, sf):
    t = chat.as_transcripts(spark.read.parquet(sf.replace("0.001", "0.1") + "/conversations.parquet")).collect()
    half = len(t) // 2
    m = chat.TranscriptModel.fitted([(r.transcript.split("\n"), list(r.states)) for r in t[:half]])
    right = sum([x for x, _ in m.turns(r.transcript)] == r.roles for r in t[half:])
    assert right >= 0.95 * (len(t) - half)
    assert [x for x, _ in m.turns("Human: hello there\nAI: hi\nHuman: bye")] == ["user", "assistant", "user"]
    assert m.turns(None) == [] == m.turns(" \n ")


def test_odd_conversations(spark):
    rows = [(1, 0, "user", "a"), (1, 0, "user", "a"), (1, None, "nobody", None), (None, 1, "user", "b"), (None, 2, "system", "c")]
    rows += [(7, i, ("user", "assistant")[i % 2], f"t{i}") for i in range(2500)]
    df = spark.createDataFrame([(*r, 1) for r in rows], "conv_id long, turn long, role string, text string, segment int")
    got = chat.formatted_chats(df).collect()
    assert sum(r.n_turns for r in got) == len(rows)
    assert Counter(r.conv_id for r in got) == {1: 1, None: 2, 7: 3}
    assert chat.formatted_chats(df.limit(0)).count() == 0


def test_viterbi_equals_the_best_of_all_paths():
    from itertools import product

    rng = np.random.default_rng(3)
    texts = ["Hello there.", "What is it?", "", "User: hi", "Assistant: yes", "more of it " * 9, "[SYSTEM] be kind", "note: this"]
    labelled = []
    for style in range(8):
        roles = ["system", "user", "assistant", "user", "assistant"]
        text, states = chat._joined(roles, [texts[i] for i in rng.integers(0, 3, 5)], style)
        labelled.append((text.split("\n"), states))
    m = chat.TranscriptModel.fitted(labelled)
    n = len(chat.STATES)
    for size in (1, 2, 3, 4, 5):
        lines = [texts[i] for i in rng.integers(0, len(texts), size)]
        rows, _ = chat.line_features(lines)
        seen = sum(f[:, rows[:, j]] for j, f in enumerate(m.features)).T
        cost = lambda p: m.first[p[0]] + seen[0, p[0]] + sum(m.move[p[i - 1], p[i]] + seen[i, p[i]] for i in range(1, size))  # noqa: E731, B023
        path, _ = m.states(lines)
        assert np.isclose(cost(path), max(cost(p) for p in product(range(n), repeat=size)))


def test_clashing_columns_and_equal_turns(spark):
    rows = [(1, "User: a\nAssistant: b", "x", 5, "y"), (2, None, "x", 6, "y")]
    df = spark.createDataFrame(rows, "conv_id long, transcript string, turns string, `odd name:` int, Chat string")
    m = chat.TranscriptModel.fitted([(["User: a", "Assistant: b"], [2, 4])])
    got = chat.parse_transcripts(df, m)
    assert got.columns == ["conv_id", "transcript", "odd name:", "turns", "chat"]
    assert {r.conv_id: len(r.turns) for r in got.collect()} == {1: 2, 2: 0}
    same = spark.createDataFrame([(7, 1, "user", "again")] * 3000 + [(8, 1, "user", "once")], "conv_id long, turn long, role string, text string")
    parts = chat.as_transcripts(same).collect()
    assert sum(r.n_turns for r in parts if r.conv_id == 7) == 3000 and max(r.n_turns for r in parts) <= chat.SEGMENT_TURNS
    again = chat.as_transcripts(same.repartition(5)).collect()
    assert sorted((r.conv_id, r.segment, r.n_turns) for r in again) == sorted((r.conv_id, r.segment, r.n_turns) for r in parts)


def test_very_long_pages_and_transcripts():
    page = "<html><body><article>" + "".join(f"<p>Paragraph {i} with words enough to be prose in it.</p>" for i in range(20_000)) + "</article></body></html>"
    assert main_text(page).count("\n") == 19_999
    m = chat.TranscriptModel.fitted([(["User: a", "Assistant: b"], [2, 4])])
    assert len(m.turns("\n".join(f"User: line {i}" for i in range(5000)))) == 5000


def test_ties_between_articles():
    half = "<article><p>Equal words in equal articles, both of the same length here.</p></article>"
    assert main_text(f"<body>{half}{half}</body>").split("\n") == ["Equal words in equal articles, both of the same length here."] * 2
