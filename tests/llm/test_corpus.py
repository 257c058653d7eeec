"""The corpus operators against brute force, exact round trips, and edge cases."""

import hashlib
import math
import random
import re
import time
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from tilebalance.llm import bpe, fingerprints, fuzzylines, htmltext, mixing, quotations, setjoin, substrings, toxicity, vectors
from tilebalance.llm.common import connected_components
from tilebalance.llm.queries import codec

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SF = "/root/testdata/sf0.001"
#: Nulls, empties, ties, repeats, odd white space and one very long text.
ODD = [None, "", "   ", "a", "a b", "a b", "\x1c x\x85y z\xa0w", "é" * 9, "word " * 3000, "word " * 3000, "Word " * 2999 + "other"]


def rows_of(spark, texts, start=0):
    return spark.createDataFrame([(start + i, t, "x", f"src{i % 3}" if i % 4 else None, 1) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")


def corpus(seed, n, vocabulary=60, most=80):
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(vocabulary)]
    out = []
    for _ in range(n):
        if out and rng.random() < 0.5:
            t = rng.choice(out).split(" ")
            for _ in range(rng.randrange(3)):
                t[rng.randrange(len(t))] = rng.choice(words)
            if rng.random() < 0.3:
                t = t + rng.choice(out).split(" ")
        else:
            t = rng.choices(words, k=rng.randrange(1, most))
        out.append(" ".join(t))
    return out


def roots_of(nodes, links):
    up = {n: n for n in nodes}

    def find(x):
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        up[max(a, b)] = min(a, b)
    return {n: find(n) for n in nodes}


def test_components(spark):
    rng = random.Random(1)
    links = [(rng.randrange(300), rng.randrange(300)) for _ in range(200)] + [(i, i + 1) for i in range(400, 440)] + [(500, i) for i in range(501, 560)] + [(7, 7)]
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    want = roots_of({x for p in links for x in p}, links)
    assert got == {k: v for k, v in want.items() if k in got} and set(got) == {x for a, b in links if a != b for x in (a, b)}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


# vectors


def test_vectors(spark):
    rng = np.random.default_rng(0)
    base = rng.normal(size=(12, 64))
    rows = []
    for i in range(240):
        b = base[i % 12] / np.linalg.norm(base[i % 12])
        r = rng.normal(size=64)
        r -= b * (r @ b)
        c = rng.uniform(0.955, 1)
        rows.append((i, ((c * b + math.sqrt(1 - c * c) * r / np.linalg.norm(r)) * rng.uniform(0.1, 9)).astype("f4").tolist(), i % 12 % 3, "x"))
    rows += [(1000 + i, rows[5][1], rows[5][2], "x") for i in range(9)]
    rows += [(2000, None, 1, "x"), (2001, [0.0] * 64, 1, None), (2002, [float("nan")] * 64, 1, ""), (2003, rows[7][1], None, ""), (2004, [1.0, 2.0], 0, ""), (2005, [2.0, 4.0], 0, ""), (2006, [1.0, None], 0, ""), (2007, [], 0, "")]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int, rep string")  # a clashing column too
    by, links = defaultdict(list), []
    for i, e, label, _ in rows:
        if e and label is not None and None not in e and np.isfinite(e).all() and any(e):
            by[label, len(e)].append((i, np.array(e, float) / np.linalg.norm(np.array(e, float))))
    for group in by.values():
        x = np.stack([v for _, v in group])
        links += [(group[a][0], group[b][0]) for a, b in np.argwhere(np.triu(x @ x.T >= 0.93, 1))]
    degree = Counter(x for p in links for x in p)
    roots = roots_of([r[0] for r in rows], links)
    for block in (2048, 20):
        got = {r["vec_id"]: r for r in vectors.near_duplicates(df, block=block).collect()}
        assert len(got) == len(rows)
        assert sum(r["n_links"] for r in got.values()) >= 0.98 * 2 * len(links)
        assert all(got[i]["n_links"] <= degree[i] for i in got)
        assert all(got[i]["component_id"] == roots[i] and got[i]["kept"] == (roots[i] == i) for i in got)
    assert vectors.near_duplicates(df.limit(0)).count() == 0


def test_hadamard_keeps_lengths():
    x = np.random.default_rng(1).normal(size=(5, 8))
    y = vectors._rotate(x, np.random.default_rng(2).choice([-1.0, 1.0], (3, 8)))
    assert np.allclose((x**2).sum(1), (y**2).sum(1))


# quotations


def test_quotations(spark):
    messages = [
        (1, 0, "user", "Hello there.\nHow are you today?", 5),
        (1, 1, "bot", "> How are   YOU today?\nFine, thanks.", 5),
        (1, 2, "user", "Something else.", 5),
        (1, 3, "bot", ">> How are you today?\n> Fine, thanks.\nGood.\n\n> Hello there.\nBye.", 5),
        (1, 4, "user", "> Good.\n> Bye.\nOK", 5),
        (2, 0, "user", "> Something else.\nReally?", 5),
        (2, 1, "user", "> never said\n> ???\nx", 5),
        (3, 0, "user", None, 5), (3, 1, "user", "", None), (None, 0, "user", "> Good.\ny", 5), (3, 2, "user", ">", 5), (1, 4, "user", "> Good.\n> Bye.\nOK", 5),
    ]
    df = spark.createDataFrame(messages, "conv_id long, turn long, role string, text string, depth long")
    got = defaultdict(list)
    for r in quotations.reply_order(df).collect():
        got[r["conv_id"], r["turn"]].append((r["clean_text"], r["n_quoted"], r["max_level"], r["n_linked"], r["parent_turn"], r["thread_turn"], r["depth"], r["path"]))
    assert got[1, 1] == [("Fine, thanks.", 1, 1, 1, 0, 0, 1, [0, 1])]
    assert got[1, 3] == [("Good.\n\nBye.", 3, 2, 3, 1, 0, 2, [0, 1, 3])]
    assert got[1, 4] == [("OK", 2, 1, 1, 3, 0, 3, [0, 1, 3, 4])] * 2
    assert got[1, 2][0][4:] == (None, 2, 0, [2])
    assert got[2, 0] == [("Really?", 1, 1, 1, None, 0, 0, [0])]  # from another conversation: linked, but no reply within this one
    assert got[2, 1] == [("x", 2, 1, 0, None, 1, 0, [1])]
    assert got[3, 0][0][:4] == ("", 0, 0, 0) and got[None, 0][0][0] == "y"
    where = {(r["conv"], r["turn"], r["passage"]): (r["level"], r["from_conv"], r["from_turn"]) for r in quotations.passages(df).collect()}
    assert where[2, 0, 0] == (1, 1, 2) and where[1, 3, 0] == (2, 1, 0) and where[1, 3, 1] == (1, 1, 1) and where[2, 1, 0] == (1, None, None)
    assert quotations.reply_order(df.limit(0)).count() == 0


def test_quotations_from_other_conversations(spark):
    messages = [
        (1, 0, "user", "Line alpha."), (1, 1, "bot", "> Line alpha.\n> Line beta.\nYes."),
        (2, 0, "user", "Line beta."), (9, 0, "user", "Line alpha.\nLine beta."), (9, 1, "bot", "Line gamma."),
        (0, 0, "user", "> Line gamma.\n\n> Line delta."), (0, 1, "user", "Line gamma.\nLine delta."),  # the least row is a later turn of the same conversation
        (5, 0, "user", "> Line alpha.\n> Line beta."), (6, 0, "user", "Line delta."), (7, 3, "user", "Line delta."),
    ]
    messages += [(20 + i, 0, "user", "Line alpha.") for i in range(40)] + [(70 + i, 0, "user", "> Line alpha.") for i in range(40)]
    df = spark.createDataFrame(messages, "conv_id long, turn long, role string, text string")
    where = {(r["conv"], r["turn"], r["passage"]): (r["found"], r["from_conv"], r["from_turn"]) for r in quotations.passages(df).collect()}
    assert where.pop((1, 1, 0)) == (1, 1, 0)  # an earlier turn of the same conversation comes first
    assert where.pop((5, 0, 0)) == (2, 9, 0)
    assert where.pop((0, 0, 0)) == (1, 9, 1) and where.pop((0, 0, 2)) == (1, 6, 0)
    assert where == {(70 + i, 0, 0): (1, 1, 0) for i in range(40)}
    linked = {(r["conv_id"], r["turn"]): r["n_linked"] for r in quotations.reply_order(df).collect()}
    assert linked[0, 0] == 2


def test_quotations_against_every_message(spark):
    """Sources, parents and paths by comparing each passage with every message."""
    rng = random.Random(8)
    said = [f"Sentence {w}." for w in "abcdefghij"] + ["---", ""]
    messages = []
    for conv in range(25):
        for turn in range(rng.randrange(1, 8)):
            lines = []
            for _ in range(rng.randrange(1, 5)):
                level = rng.choice([0, 0, 1, 1, 2])
                lines += [">" * level + " " * (level > 0) + (x.upper() if rng.random() < 0.2 else x) for x in rng.choices(said, k=rng.randrange(1, 4))]
            messages.append((conv, turn, "user", "\n".join(lines)))
    level = lambda x: re.match(r"[ \t]*(?:>[ \t]?)*", x)[0].count(">")
    norm = lambda x: " ".join(re.sub(r"^[ \t]*(?:>[ \t]?)+", "", x).lower().split())
    word = lambda x: re.search(r"\w", x)
    own = {(c, t): {norm(x) for x in text.split("\n") if not level(x) and word(x)} for c, t, _, text in messages}
    passages, parents, linked = {}, {}, Counter()
    for c, t, _, text in messages:
        lines, at = text.split("\n"), 0
        while at < len(lines):
            n, depth = 1, level(lines[at])
            while at + n < len(lines) and level(lines[at + n]) == depth:
                n += 1
            if depth:
                held = [norm(x) for x in lines[at : at + n] if word(norm(x))]
                votes = {m: sum(x in ls for x in held) for m, ls in own.items()}
                near = [(v, m[1], m) for m, v in votes.items() if v and m[0] == c and m[1] < t]
                far = [(-v, m) for m, v in votes.items() if v and m[0] != c]
                best = max(near)[2] if near else min(far)[1] if far else None
                passages[c, t, at] = (depth, n, votes[best] if best else 0, *(best or (None, None)))
                linked[c, t] += best is not None
                if depth == 1 and best and best[0] == c:
                    parents.setdefault((c, t), best[1])
            at += n
    df = spark.createDataFrame(messages, "conv_id long, turn long, role string, text string")
    got = {(r["conv"], r["turn"], r["passage"]): (r["level"], r["lines"], r["found"], r["from_conv"], r["from_turn"]) for r in quotations.passages(df).collect()}
    assert got == passages and parents
    for r in quotations.reply_order(df).collect():
        c, path = r["conv_id"], [r["turn"]]
        while (c, path[0]) in parents:
            path.insert(0, parents[c, path[0]])
        assert r["path"] == path and r["depth"] == len(path) - 1 and r["thread_turn"] == path[0]
        assert r["parent_turn"] == parents.get((c, r["turn"])) and r["n_linked"] == linked[c, r["turn"]]


# html


def test_html():
    page = """<!DOCTYPE html><html><head><title>T</title><style>p{}</style><script>var a="</p>";</script></head><body>
    <header class="top"><a href="/">Home</a></header><nav><ul><li><a>One</a><li><a>Two</a></ul></nav><div class="cookie-notice">We use cookies on this site, accept?</div>
    <div class="wrap"><article><header><h1>The  head &amp; more</h1></header><p>First <b>bold</b>
    text&nbsp;here.<p>Second one<br>broken &lt;line&gt;</p><div class="ad">Buy now</div><aside>Aside</aside><form><input><p>mail</p></form><ul><li>item</li></ul>
    <!-- <p>hidden</p> --><p>2 < 3 and a > b</p><section id="comments"><p>nice post</p></section></article></div>
    <div class="sidebar"><p>Side text that is rather long, so that it would count as text of the article if it were allowed to.</p></div><footer><p>&copy; foot</p></footer></body></html>"""
    assert htmltext.main_text(page) == "The head & more\nFirst bold text here.\nSecond one\nbroken <line>\nitem\n2 < 3 and a > b"
    plain = "<body><div><a href=1>Menu</a> <a href=2>More</a></div>" + "".join(f"<p>Paragraph number {i} has a good number of words that make it text.</p>" for i in range(4)) + "<div><a>next</a> <a>last</a></div><script>x"
    assert htmltext.main_text(plain) == "\n".join(f"Paragraph number {i} has a good number of words that make it text." for i in range(4))
    assert htmltext.main_text(None) == htmltext.main_text("") == htmltext.main_text("<p></p>") == ""
    assert htmltext.main_text("just words") == "just words"
    assert htmltext.surges([0, 5, 90, 40, 0, 0, 0, 30]) == [(1, 4)]


PARA = "A paragraph that is long enough to be the text of an article, with commas, and a good many more words than a menu."


@pytest.mark.parametrize(
    ("page", "text"),
    [
        # class words told from what only holds them, and an element around the article
        (f'<div class="layout has-sidebar"><article><h1>T</h1><p>{PARA}</p></article></div>', f"T\n{PARA}"),
        (f'<div class="post no-comments"><p>{PARA}</p></div>', PARA),
        (f'<div class="entry print"><p>{PARA}</p></div>', PARA),
        (f'<div class="menu"><article><p>{PARA}</p></article></div>', PARA),
        (f'<div class="sidebar"><p>{PARA}</p></div>', PARA),
        (f'<div class="post"><div class="post-header"><h1>Title</h1></div><p>{PARA}</p></div><div class="left-sidebar">{PARA}</div>', f"Title\n{PARA}"),
        (f'<article><h1>T</h1><div class="entry-header">by me</div><p>{PARA}</p><div class="share-box">{PARA}</div></article>', f"T\nby me\n{PARA}"),
        # comments are articles of their own
        (f'<article><p>{PARA}</p></article><ol class="comment-list"><li><article class="comment-body"><p>{PARA * 9}</p></article></ol>', PARA),
        # a form around the page
        (f'<form id="page"><div id="header"><a>x</a></div><h1>T</h1><p>{PARA}</p><input></form>', f"T\n{PARA}"),
        # nothing of the article is dropped: short and linked lines
        (f"<article><p>{PARA}</p><p><a>See the source here</a></p><p>Yes.</p></article>", f"{PARA}\nSee the source here\nYes."),
        (f"<p>{PARA}</p><p><a>See the source here</a></p><p>{PARA}</p>", f"{PARA}\nSee the source here\n{PARA}"),
        (f"<p>{PARA * 20}</p><ul>" + "<li><a>link list</a></li>" * 8 + f"</ul><p>{PARA}</p>", f"{PARA * 20}\n{PARA}"),
        ("<article><h1>Short</h1><p>one</p></article><div>Elsewhere</div>", "Short\none"),
        # a marked element that holds next to nothing is not believed
        (f"<article>short.</article><p>{PARA * 5}</p>", f"short.\n{PARA * 5}"),
        # menus and notices without marks, and rights
        (f"<div><a>Home</a> | <a>News</a></div><p>{PARA}</p><div>© 2020 Someone</div>", PARA),
        # quotes in bare values, comments, cut-off markup, cells
        ("<article><p>a <a href=o'neil.html>b</a> c</p><p title=\"x>y\">d<!-- > --></p><p>e &lt;f&gt; <", "a b c\nd\ne <f> <"),
        ("<main><table><tr><td>a<td>b<tr><td>c</table><p>d<div>e", "a\nb\nc\nd\ne"),
        ("<article><script>if (a < b) '</p>'</script><p hidden>x</p><p style='display: none'>y</p>z", "z"),
    ],
)
def test_html_pages(page, text):
    assert htmltext.main_text(page) == text


@pytest.mark.parametrize("marked", [False, True])
def test_html_against_definition(marked):
    """Pages of paragraphs, links and menus: the lines kept are those of windows that surge, to where lines dive."""
    rng = random.Random(5)
    for _ in range(300):
        rows = [(rng.choice([3, 10, 30, 90, 200]), rng.random() < 0.4, marked and rng.random() < 0.7) for _ in range(rng.randrange(1, 25))]
        page = "".join(("<article>" if inside else "") + ("<p><a>{}</a></p>" if linked else "<p>{}</p>").format("x" * n) + ("</article>" if inside else "") for n, linked, inside in rows)
        counts = [0 if linked else n for n, linked, _ in rows]

        def runs(counts):
            text, high = [c > 0 for c in counts], [sum(counts[i : i + 3]) >= 80 for i in range(len(counts))]
            # a line is kept if from some surge on there is no dive up to it
            return [any(text[s] and high[s] and all(text[k] or high[k] for k in range(s, i + 1)) for s in range(i + 1)) for i in range(len(counts))]

        if any(inside for _, _, inside in rows):
            weighed = [4 * c if inside else c for c, (_, _, inside) in zip(counts, rows, strict=True)]
            on, pieces = runs(weighed), []
            for i, k in enumerate(on):
                if k and i and on[i - 1] and not (weighed[i - 1] == 0 and sum(weighed[i - 1 : i + 2]) < 80):
                    pieces[-1].append(i)
                elif k:
                    pieces.append([i])
            best = max(pieces or [list(range(len(rows)))], key=lambda p: sum(weighed[i] for i in p))
            if 2 * sum(weighed[i] for i in best if rows[i][2]) >= sum(weighed[i] for i in best):
                counts = [max(c, 80) if inside else 0 for c, (_, _, inside) in zip(counts, rows, strict=True)]
        kept = runs(counts)
        want = ["x" * n for (n, _, _), k, c in zip(rows, kept, counts, strict=True) if (k if any(kept) else c > 0)]
        assert htmltext.main_text(page) == "\n".join(want)


def test_html_of_any_nesting_in_proportion():
    """Time grows in proportion: a page of a megabyte of unclosed elements takes seconds, not hours."""
    began = time.perf_counter()
    assert htmltext.main_text("<b>" * 100_000 + "x" + "</i>" * 100_000 + "</b>" * 100_000) == "x"
    assert htmltext.main_text("<b><td>" + "<i>" * 100_000 + "</b>" * 100_000 + "<p>a" * 10_000) == "\n".join("a" * 10_000)
    assert htmltext.main_text("<div>" * 100_000 + "y" * 100 + "<a href=\"" * 1000 + "<!--" * 1000) == "y" * 100
    assert time.perf_counter() - began < 60


def test_html_frame(spark):
    df = spark.createDataFrame([(1, "u", "<article><p>é x</p></article>", "old", 9), (2, None, None, None, None)], "page_id long, url string, html string, text string, n_chars long")
    got = {r["page_id"]: (r["url"], r["text"], r["n_chars"]) for r in htmltext.extract(df).collect()}
    assert got == {1: ("u", "é x", 3), 2: (None, "", 0)}
    assert htmltext.extract(df.limit(0)).count() == 0


# mixing


def poured(sizes, weights, share=1.5, most=2):
    """Targets by pouring what is above a cap over the rest, again and again."""
    total, out, left = share * sum(sizes.values()), {}, dict(sizes)
    while True:
        w = sum(weights[s] for s in left)
        over = [s for s in left if total * weights[s] / w > most * left[s] + 1e-9] if w else []
        if not over:
            return out | {s: total * weights[s] / w for s in left}
        for s in over:
            out[s] = most * left[s]
            total -= out[s]
            del left[s]


@pytest.mark.parametrize("seed", [1, 2])
def test_mixing(spark, seed):
    rng = random.Random(seed)
    rows = [(i, " ".join("w" for _ in range(rng.choice([0, 1, 5, 5, 5, 40, 300]))), rng.choice(["b", "a", "é", None, "c", "c", "c"])) for i in range(700)] + [(9000, None, "a"), (9001, "  \t ", None), (9002, "x y", "tiny")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = [r.asDict() for r in mixing.mixed(df, mixing.words()).collect()]
    again = {r["doc_id"]: r["taken"] for r in mixing.mixed(df.repartition(5), mixing.words()).collect()}
    assert len(got) == len(rows) and {r["doc_id"]: r["taken"] for r in got} == again
    source = {i: s for i, _, s in rows}
    sizes = Counter()
    for i, t, s in rows:
        sizes[s] += len(WORD.findall(t or ""))
    order = sorted((s for s in sizes if s is not None), key=lambda s: s.encode()) + [None]
    want = poured(dict(sizes), {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)})
    taken = Counter()
    for r in got:
        s = source[r["doc_id"]]
        taken[s] += r["taken"]
        assert r["source_size"] == sizes[s] and abs(r["target"] - want[s]) < 1e-6 and r["taken"] in (0, r["size"], 2 * r["size"])
    for s in sizes:
        assert abs(taken[s] - want[s]) <= max(2, 0.01 * want[s]), (s, taken[s], want[s])
    assert mixing.mixed(df.limit(0), mixing.words()).count() == 0


def test_tilts_solve_the_dual(spark):
    cells = spark.createDataFrame([("a", s, n) for s, n in ((1, 50), (10, 30), (200, 3))] + [("b", 7, 11)], "source string, size long, n long")
    targets = spark.createDataFrame([("a", 950, 700.0), ("b", 77, 154.0)], "source string, source_size long, target double")
    got = {r["source"]: r for r in mixing.tilts(cells, targets).collect()}
    rate = lambda s: min(2.0, math.exp(got["a"]["tilt"] * s / got["a"]["scale"]))
    assert abs(50 * rate(1) + 300 * rate(10) + 600 * rate(200) - 700) < 1e-5 and got["b"]["tilt"] is None


# substrings


def repeats(docs, window):
    """Brute force: kept words of each document."""
    first, out = {}, {}
    split = {i: WORD.findall(t or "") for i, t in docs}
    for i in sorted(split):
        for k in range(len(split[i]) - window + 1):
            first.setdefault(tuple(split[i][k : k + window]), i)
    for i, ws in split.items():
        gone = set()
        for k in range(len(ws) - window + 1):
            if first[tuple(ws[k : k + window])] < i:
                gone.update(range(k, k + window))
        out[i] = (len(ws), len(gone), hashlib.sha256(" ".join(w for k, w in enumerate(ws) if k not in gone).encode()).hexdigest())
    return out


@pytest.mark.parametrize(("window", "anchor", "crowd"), [(7, 3, 2000), (7, 3, 2), (50, 8, 2000)])
def test_substrings(spark, window, anchor, crowd):
    texts = corpus(3, 120, 4 if window < 10 else 60, 120) + ODD
    df = rows_of(spark, texts)
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substrings.digests(df, window=window, anchor=anchor, crowd=crowd, shard_words=3000).collect()}
    assert got == repeats(list(enumerate(texts)), window)
    if window == 50:
        kept = {r["doc_id"]: r["text"] for r in substrings.deduplicated(df).collect()}
        assert all(hashlib.sha256(kept[i].encode()).hexdigest() == got[i][2] for i in got)
        assert substrings.digests(df.limit(0)).count() == 0


@pytest.mark.parametrize("crowd", [2000, 1])
def test_substrings_repeated_within_a_document(spark, crowd):
    rng = random.Random(4)
    some = lambda n: [f"u{rng.randrange(10**6)}" for _ in range(n)]
    texts = []
    for _ in range(6):
        p, x, y = some(30), some(10), some(12)
        texts.append(some(20) + p + some(20))
        texts.append(some(15) + x + p + y + some(9) + x + p + y + some(5))
        q = some(25)
        texts += [some(3) + q + some(4), q * 4]
    texts = [" ".join(t) for t in texts]
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substrings.digests(rows_of(spark, texts), window=12, anchor=3, crowd=crowd, shard_words=300).collect()}
    assert got == repeats(list(enumerate(texts)), 12)


def test_fm_index():
    rng = np.random.default_rng(1)
    for _ in range(10):
        w = int(rng.integers(2, 9))
        docs = [rng.integers(0, 4, int(rng.integers(0, 60))).astype(np.uint64) for _ in range(12)]
        keys, seen = np.arange(12) * 3, {}
        for i, d in enumerate(docs):
            for j in range(len(d) - w + 1):
                seen.setdefault(tuple(d[j : j + w]), keys[i])
        index = substrings.FmIndex(np.concatenate(docs), np.array([len(d) for d in docs]), keys, w)
        query = rng.integers(0, 5, 200).astype(np.uint64)  # with words the index has not
        found = index.first_owners(query, np.array([120, 80]), w)
        for a, n in ((0, 120), (120, 80)):
            for j in range(n):
                assert found[a + j] == (seen.get(tuple(query[a + j : a + j + w]), substrings.NONE) if j + w <= n else substrings.NONE)
        values = rng.integers(0, 6, 300)
        tree = substrings.WaveletTree(values, 3)
        at, symbol = rng.integers(0, 301, 50), rng.integers(0, 6, 50)
        assert tree.rank(symbol, at).tolist() == [int((values[:a] == s).sum()) for a, s in zip(at, symbol, strict=True)]


# fuzzy lines


def _norm(line):
    return re.sub(r"[^\w]+|_", " ", line.lower()).strip()


def _distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def test_fuzzy_lines(spark):
    rng = random.Random(5)
    words = [f"w{i}" for i in range(300)]
    lines = [" ".join(rng.choices(words, k=40)) for _ in range(12)]
    texts = []
    for _ in range(90):
        own = []
        for _ in range(rng.randrange(1, 6)):
            line = rng.choice(lines).split(" ")
            if rng.random() < 0.6:
                line[rng.randrange(40)] = rng.choice(words)
            own.append((" ".join(line) + rng.choice(["", ".", "!"])).upper() if rng.random() < 0.2 else " ".join(line))
        texts.append("\n".join([*own, "", rng.choice(["---", "short line", "an other short line"])]))
    texts += ["", None, "---\n\n---", "short line\nshort line\nSHORT, line", "only " * 5000, "only " * 5000]
    df = rows_of(spark, texts)
    found, distinct = fuzzylines.lines(df)
    hashed = found.join(distinct.select("h1", "h2", "id"), ["h1", "h2"]).join(fuzzylines.simhashes(distinct), "id")
    found = {(r["key"], r["line"]): (r["id"], r["size"], r["s0"]) for r in hashed.collect()}
    where = defaultdict(list)
    norm = {}
    for i, t in enumerate(texts):
        for k, line in enumerate((t or "").split("\n")):
            if _norm(line):
                assert (i, k) in found
                where[found[i, k]].append((i, k))
                norm[found[i, k]] = _norm(line).split(" ")
    assert sum(map(len, where.values())) == len(found)
    nodes = sorted(where)
    links = []
    for x in range(len(nodes)):
        for y in range(x):
            a, b = nodes[x], nodes[y]
            if ((a[2] ^ b[2]).bit_count() <= 3 or ((a[2] ^ b[2]) & (2**64 - 1)).bit_count() <= 3) and min(a[1], b[1]) >= 0.8 * max(a[1], b[1]):
                if 1 - _distance(norm[a], norm[b]) / max(a[1], b[1]) >= 0.8 - 1e-9:
                    links.append((a, b))
    assert links
    groups = defaultdict(list)
    for node, root in roots_of(nodes, links).items():
        groups[root] += where[node]
    want = {p for g in groups.values() for p in sorted(g)[1:]}
    assert {(r["doc_id"], r["line"]) for r in fuzzylines.removals(df, bits=3).collect()} == want
    df = df.selectExpr("*", "1 as key", "2 as lost", "3 as _key", "4 as line", "5 as n_removed")
    done = {r["doc_id"]: (r["text"], r["n_removed"]) for r in fuzzylines.deduplicated(df, bits=3).where("key = 1 and lost = 2 and _key = 3 and line = 4").collect()}
    for i, t in enumerate(texts):
        kept = None if t is None else "\n".join(x for k, x in enumerate(t.split("\n")) if (i, k) not in want)
        assert done[i] == (kept, sum(p[0] == i for p in want))
    assert fuzzylines.deduplicated(df.limit(0)).count() == 0


def test_fuzzy_lines_by_edit_similarity_alone(spark):
    rng = random.Random(6)
    words = [f"w{i}" for i in range(150)]
    texts = []
    bases = [rng.choices(words, k=n) for n in (3, 4, 4, 5, 5, 6, 7, 8, 9, 10, 10, 14, 15, 19, 20, 25, 50) for _ in range(2)]
    for _ in range(260):
        line = list(rng.choice(bases))
        for _ in range(rng.randrange(len(line) // 4 + 1)):
            at = rng.randrange(len(line))
            line[at : at + rng.randrange(2)] = rng.choices(words, k=rng.randrange(2))
        texts.append(" ".join(line))
    # edits as far apart as can be
    even = [f"e{i}" for i in range(20)]
    texts += [" ".join(even), " ".join(f"x{i}" if i % 5 == 4 else w for i, w in enumerate(even)), " ".join(["a"] * 30), " ".join(["a"] * 25 + ["b"] * 5)]
    lines = [(i, _norm(t).split(" ")) for i, t in enumerate(texts) if _norm(t)]
    links = [(i, j) for i, a in lines for j, b in lines if j < i and 1 - _distance(a, b) / max(len(a), len(b)) >= 0.8 - 1e-9]
    want = {(i, 0) for i, root in roots_of([i for i, _ in lines], links).items() if root < i}
    assert {(r["doc_id"], r["line"]) for r in fuzzylines.removals(rows_of(spark, texts)).collect()} == want
    # the gate of three bits misses some of them
    assert {(r["doc_id"], r["line"]) for r in fuzzylines.removals(rows_of(spark, texts), bits=3).collect()} < want
    assert fuzzylines.deduplicated(rows_of(spark, texts).limit(0)).count() == 0


def test_fuzzy_lines_of_many_words(spark, monkeypatch):
    rng = random.Random(61)
    words = [f"w{i}" for i in range(400)]
    bases = [rng.choices(words, k=n) for n in (5, 6, 7, 10, 15, 16, 25, 101, 103, 120, 127, 128, 160, 300)]
    lines = []
    for base in bases:
        for _ in range(6):
            line = list(base)
            for _ in range(rng.randrange(len(line) // 4 + 1)):
                at = rng.randrange(len(line))
                line[at : at + rng.randrange(2)] = rng.choices(words, k=rng.randrange(2))
            lines.append(line)
        # every fifth word changed: as few runs as can be are left
        lines += [base, [f"x{i}" if i % 5 == 4 else w for i, w in enumerate(base)], [f"y{i}" if i % 5 == 2 else w for i, w in enumerate(base)]]
    most = lambda a, b: int(max(len(a), len(b)) / 5 + 1e-9)
    links = [(i, j) for i, a in enumerate(lines) for j, b in enumerate(lines) if j < i and abs(len(a) - len(b)) <= most(a, b) and _distance(a, b) <= most(a, b)]
    want = {(i, 0) for i, root in roots_of(range(len(lines)), links).items() if root < i}
    texts = rows_of(spark, [" ".join(x) for x in lines])
    assert {(r["doc_id"], r["line"]) for r in fuzzylines.removals(texts).collect()} == want
    monkeypatch.setattr(fuzzylines, "MANY", 0)
    assert {(r["doc_id"], r["line"]) for r in fuzzylines.removals(texts).collect()} == want


def test_long_lines_of_common_words_do_not_meet(spark):
    rng = random.Random(62)
    words = [f"w{i}" for i in range(300)]
    texts = [" ".join(rng.choices(words, weights=[1 / (i + 1) for i in range(300)], k=250)) for _ in range(60)]
    placed = fuzzylines.placed_by_words(fuzzylines.lines(rows_of(spark, texts))[1])
    pairs = placed.alias("p").join(placed.alias("q"), "bucket").where("p.id < q.id").select("p.id", "q.id").distinct().count()
    assert pairs < 60 * 59 // 2 // 2


def test_sketches_of_lines_are_stored_once_for_each_line(spark, monkeypatch):
    """Not once for each bucket that a line is in, as such rows are many and do not pack."""
    rng = random.Random(63)
    bases = [[f"w{rng.randrange(90)}" for _ in range(20)] for _ in range(12)]
    texts = [" ".join(w if rng.random() > 0.08 else "x" for w in base) for base in bases for _ in range(6)]
    stored = []

    def recorded(df, label, keep=fuzzylines.stash):
        done = keep(df, label)
        stored.append((set(done.columns), done.count()))
        return done

    monkeypatch.setattr(fuzzylines, "stash", recorded)
    monkeypatch.setattr(fuzzylines, "TURNS", 2)
    monkeypatch.setattr(fuzzylines, "TURNS_ALL", 2, raising=False)
    done = {(r["doc_id"], r["line"]) for r in fuzzylines.removals(rows_of(spark, texts)).collect()}
    words = [_norm(t).split(" ") for t in texts]
    links = [(i, j) for i, a in enumerate(words) for j, b in enumerate(words) if j < i and _distance(a, b) <= 4]
    assert done == {(i, 0) for i, root in roots_of(range(len(texts)), links).items() if root < i}
    assert all(n <= len(texts) for columns, n in stored if "s0" in columns) and not any({"bucket", "s0"} <= columns for columns, _ in stored)


# n-gram Jaccard join


def shingles(t, n=3):
    w = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set())


@pytest.mark.parametrize("block", [400, 3])
def test_set_join(spark, block):
    texts = corpus(7, 150, 400, 90) + ODD + [" ".join(f"v{i}" for i in range(k)) for k in (3, 11, 12, 13, 22)]
    sets = {i: shingles(t) for i, t in enumerate(texts)}
    links = [(a, b) for a in sets for b in range(a) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 90 * len(sets[a] | sets[b])]
    roots = roots_of(list(sets), links)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in setjoin.components(rows_of(spark, texts), block=block).collect()}
    assert got == {i: (len(s), roots[i]) for i, s in sets.items()}
    if block == 3:
        assert setjoin.components(rows_of(spark, texts).limit(0)).count() == 0


def test_shared_tokens_of_any_size_in_a_range(spark):
    ranges = [(n, a, b) for n in range(1, 60) for a in range(-(-n * 9 // 10), n * 10 // 9 + 1) for b in range(a, n * 10 // 9 + 1)]
    df = spark.createDataFrame(ranges, "n long, a long, b long")
    least = lambda n, x: -(-90 * (n + x) // 190) - -(-90 * max(n, x) // 100) + 1
    for r in df.select("*", setjoin._shared(F.col("n"), F.col("a"), F.col("b"), 90).alias("need")).collect():
        every = [least(r["n"], x) for x in range(r["a"], r["b"] + 1)]
        assert r["need"] == max(1, min(every)), r


# fingerprints


def test_fingerprints(spark):
    texts = corpus(11, 60, 500, 600) + ODD
    got = {r["doc_id"]: r for r in fingerprints.compared(rows_of(spark, texts).repartition(3)).collect()}
    errors = []
    for i, t in enumerate(texts):
        t, n = t or "", texts[(i + 1) % len(texts)] or ""
        half = len(t) // 2
        edited = t[: len(t) - half] + n[:half]
        r = got[i]
        assert r["n_chars"] == len(t) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert 0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1
        for value, other in ((r["near_edited"], edited), (r["near_next"], n)):
            a, b = shingles5(t), shingles5(other)
            errors.append(value - (len(a & b) / len(a | b) if a | b else 1.0))
    assert np.sqrt(np.mean(np.square(errors))) < 0.05 and np.abs(errors).max() < 0.2
    assert got[texts.index("a b")]["fingerprint"] == got[texts.index("a b") + 1]["fingerprint"]
    one = {r["doc_id"]: r["near_next"] for r in fingerprints.compared(rows_of(spark, ["a b c d e f"])).collect()}
    assert one == {0: 1.0} and fingerprints.compared(rows_of(spark, texts).limit(0)).count() == 0


def shingles5(t):
    w = WORD.findall(t)
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


# toxicity


def test_toxicity(spark):
    rng = random.Random(13)
    words = [f"w{i}" for i in range(400)]
    bad = ["grobian", "grobianus", "schuft", "schuftig"]
    rows, labels = [], []
    for i in range(600):
        y = int(rng.random() < 0.3)
        t = rng.choices(words, k=rng.randrange(5, 60)) + (rng.choices(bad, k=3) if y else [])
        rng.shuffle(t)
        rows.append((i, " ".join(t), "score"))
        labels.append((i, y if i % 7 else None))
    rows += [(1000 + i, t, "x") for i, t in enumerate(ODD)]
    docs, marked = spark.createDataFrame(rows, "doc_id long, text string, score string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    scorer = toxicity.fit(docs, marked)
    got = {r["doc_id"]: r for r in toxicity.score(docs.select("doc_id", "text", toxicity.held_out().alias("h"), "score"), scorer).collect()}
    assert len(got) == len(rows) and all(0 <= r["score"] <= 1 for r in got.values())
    assert all(r["h"] == (zlib.crc32(str(i).encode()) % 5 == 0) for i, r in got.items())
    held = [(got[i]["score"] >= 0.5) == bool(y) for i, y in labels if y is not None and got[i]["h"]]
    assert np.mean(held) > 0.95
    again = toxicity.fit(docs.repartition(5), marked.repartition(3))
    same = {r["doc_id"]: r["score"] for r in toxicity.score(docs, again).collect()}
    assert all(abs(same[i] - got[i]["score"]) < 1e-6 for i in same)
    one = toxicity.score(docs, toxicity.fit(docs, marked.where("toxic = 0")))
    assert one.where("score > 0.5").isEmpty()
    none = toxicity.score(docs, toxicity.fit(docs, marked.limit(0)))
    assert {r["score"] for r in none.collect()} == {0.5} and toxicity.score(docs.limit(0), scorer).count() == 0


def kneser_ney(words, order, shared, discount):
    """log P(word | 1) - log P(word | 0) by counting strings: words is {(word, class): count}."""
    runs = [{} for _ in range(order + 1)]  # runs[k]: {run: [weight in class 0, in class 1]}
    for (w, y), n in words.items():
        padded = "\x02" * (order - 1) + w + "\x03"
        for i in range(len(w) + 1):
            runs[order].setdefault(padded[i : i + order], [0, 0])[y] += n
    here = {run: [n > 0 for n in ns] for run, ns in runs[order].items()}
    for k in range(order - 1, 0, -1):
        below = {}
        for run, classes in here.items():
            got = runs[k].setdefault(run[1:], [0, 0])
            for y in (0, 1):
                got[y] += any(classes) if k <= shared else classes[y]
            below[run[1:]] = [a or b for a, b in zip(below.get(run[1:], [False] * 2), classes, strict=True)]
        here = below
    alphabet = len(runs[1]) + 1

    def p(y, run, k):
        if k == 0:
            return 1 / alphabet
        after = [ns[y] for r, ns in runs[k].items() if r[:-1] == run[-k:-1]]
        lower = p(y, run, k - 1)
        if not sum(after):
            return lower
        return (max(runs[k].get(run[-k:], [0, 0])[y] - discount, 0) + discount * lower * sum(min(n / discount, 1) for n in after)) / sum(after)

    def evidence(w):
        padded = "\x02" * (order - 1) + w + "\x03"
        return sum(np.log(p(1, padded[i : i + order], order)) - np.log(p(0, padded[i : i + order], order)) for i in range(len(w) + 1))

    return evidence


def test_kneser_ney_models(spark):
    rng = random.Random(29)
    words = ["".join(rng.choices("abcé😀", k=rng.randrange(1, 9))) for _ in range(60)]
    counted = [(w, *(rng.choice([0, 0, 1, 3]) for _ in range(4))) for w in sorted(set(words))]
    df = spark.createDataFrame(counted, "word string, n00 long, n01 long, n10 long, n11 long")
    for order, shared, discount in ((6, 2, 1.0), (3, 1, 0.5)):
        models = toxicity._models(df.repartition(3), order, shared, discount)
        for which, folds in ((0, (0,)), (1, (1,)), (2, (0, 1))):
            want = kneser_ney({(w, y): n for w, *ns in counted for y in (0, 1) if (n := sum(ns[2 * y + f] for f in folds))}, order, shared, discount)
            asked = [*words[:20], "", "zzz", "abc", "x"]
            assert np.allclose(models[which].evidence(asked), [want(w) for w in asked], rtol=1e-4, atol=1e-4)
    nothing = toxicity._models(df.limit(0))
    assert (nothing[2].evidence(["a", ""]) == 0).all()


def test_toxicity_counts_grow_with_the_input(spark):
    """Words of labelled rows beyond the bound of the curve count too."""
    rows = [(i, f"plain{i % 7} word " + ("vile" if i % 2 else "mild"), i % 2) for i in range(400)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, y int")
    rare = spark.createDataFrame([(5000 + i, "schurkenhaft plain1", 1) for i in range(30)], docs.schema)
    both = docs.union(rare)
    labels = both.select("doc_id", F.col("y").alias("toxic"))
    scorer = toxicity.fit(both, labels, bound=20)
    assert scorer.model().evidence(["schurkenhaft"])[0] > toxicity.fit(docs, labels, bound=20).model().evidence(["schurkenhaft"])[0] + 1


def test_toxicity_takes_small_parts(spark):
    """What a task holds besides model and evidence does not grow with the rows of a batch or with the new words in it."""
    import pickle
    import tracemalloc

    import pyarrow as pa

    docs = spark.createDataFrame([(i, f"plain{i % 7} " + ("vile" if i % 2 else "mild"), i % 2) for i in range(60)], "doc_id long, text string, toxic int")
    scorer = toxicity.fit(docs, docs)
    packed, model = len(pickle.dumps(scorer)), scorer.model()
    words = [f"w{i}" for i in range(60_000)]
    want = np.concatenate([model.evidence(words[i : i + 1000]) for i in range(0, len(words), 1000)])
    tracemalloc.start()
    known = {}
    toxicity._features([" ".join(words)], model, known)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert np.array_equal([known[w] for w in words], want) and peak < 50e6
    assert len(pickle.dumps(scorer)) == packed and len(pickle.dumps(model)) <= packed  # what was unpacked does not travel
    texts = ["a" * 900_000, None, "", "b" * 1_300_000, "c" * 3_000_000, "d"]
    batch = pa.RecordBatch.from_arrays([pa.array(texts), pa.array(range(6))], ["text", "at"])
    parts = list(toxicity._slices(batch, "text"))
    assert [p.column("at").to_pylist() for p in parts] == [[0, 1, 2], [3], [4], [5]]
    assert not list(toxicity._slices(batch.slice(0, 0), "text"))


# byte-level BPE


def test_bpe(spark):
    import public_tokenizers
    import tiktoken

    c = codec()
    enc = tiktoken.Encoding("x", pat_str=public_tokenizers.PATTERN, mergeable_ranks=c.ranks, special_tokens={})
    rng = random.Random(3)
    alphabet = list("ab  \n\t'sré½²Ⅷ中文  \x1c\x85​😀<|endoftext|>don't I'LL 123٣١")
    texts = ["".join(rng.choices(alphabet, k=rng.randrange(80))) for _ in range(150)] + ODD
    df = rows_of(spark, texts)
    for resident in (400_000, 30, 0):
        got = {r["doc_id"]: tuple(r)[1:] for r in bpe.digests(df, c, resident_words=resident).collect()}
        for i, t in enumerate(texts):
            ids = enc.encode_ordinary(t or "")
            assert got[i] == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest())
    both = df.union(df)  # repeated keys are rows of their own
    ids = bpe.encode(both, c, resident_words=20)
    assert ids.count() == 2 * len(texts) and set(df.columns) < set(ids.columns)
    back = {r["doc_id"]: r["text"] for r in bpe.decode(ids.drop("text"), c).collect()}
    assert back == {i: t or "" for i, t in enumerate(texts)}
    assert bpe.digests(df.limit(0), c).count() == 0 and "text" not in bpe.encode(df, c, keep_text=False).columns


# the pipeline


def test_pipeline(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    steps = [docs]
    for _, stage in corpus_pipeline.STAGES:
        steps.append(stage(spark, steps[-1], SF).cache())
    for df in steps[1:-1]:
        assert df.columns == docs.columns and df.dtypes == docs.dtypes
    a, b, c, d, e = steps[1:]
    clean = {i for i, y in labels.items() if y == 0}
    kept = {r["doc_id"] for r in a.select("doc_id").collect()}
    assert len(clean - kept) <= 0.05 * len(clean) + 1
    assert {r["doc_id"] for r in b.select("doc_id").collect()} == kept
    assert b.where("text IS NOT NULL AND n_chars <> length(text)").join(docs.select("doc_id", F.col("text").alias("t")), "doc_id").where("text <> t").isEmpty()
    sets = {r["doc_id"]: shingles(r["text"]) for r in b.collect()}
    roots = roots_of(list(sets), [(x, y) for x in sets for y in sets if y < x and sets[x] and sets[y] and 100 * len(sets[x] & sets[y]) >= 90 * len(sets[x] | sets[y])])
    assert {r["doc_id"] for r in c.collect()} == {i for i, root in roots.items() if i == root}
    times = Counter(r["doc_id"] for r in d.select("doc_id").collect())
    assert set(times.values()) <= {1, 2} and set(times) <= {r["doc_id"] for r in c.collect()}
    assert e.count() == d.count() and "ids" in e.columns
    text = {r["doc_id"]: r["text"] for r in d.collect()}
    assert all(r["text"] == (text[r["doc_id"]] or "") for r in bpe.decode(e.select("doc_id", "ids"), codec()).collect())
    assert corpus_pipeline.run(spark, SF).count() > 0


def test_pipeline_keeps_one_of_documents_alike_in_five_words(spark):
    import corpus_pipeline

    rng = random.Random(8)
    texts = []
    for k in range(40):  # near copies on either side of the bound
        t = [f"d{k}w{i}" for i in range(100)]
        texts.append(" ".join(t))
        for at in rng.sample(range(5, 95, 10), rng.randrange(1, 4)):
            t[at] = "new"
        texts.append(" ".join(t))
    texts += ODD
    sets = {i: shingles(t, 5) for i, t in enumerate(texts)}
    links = [(a, b) for a in sets for b in range(a) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])]
    kept = {r["doc_id"] for r in corpus_pipeline.keep_one_of_each_group(spark, rows_of(spark, texts), SF).collect()}
    assert kept == {i for i, root in roots_of(list(sets), links).items() if i == root}
