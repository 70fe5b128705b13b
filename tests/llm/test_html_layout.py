"""Rendering against a plain reference over the structure that a page was written from."""

import random

import pytest

pytest.importorskip("multiscale_scatter.llm")

from multiscale_scatter.llm import html_text  # noqa: E402

HIDE = [("class=h", ""), ("style='display: none'", ""), ("hidden", ""), ("class='k h'", ""), ("id=gone", ""), ("data-x=1", "")]
SHEET = "<style>/* .v{display:none} */ .h{display:none} #gone{color:red;display:none!important} @media print{.v{display:none}} div > .inner .deep{display:none} [data-x='1']{display:none} p:hover{display:none}</style>"


def word(r):
    return "".join(r.choice("abcdefghij") for _ in range(r.randrange(1, 7)))


def sentence(r):
    return " ".join(word(r) for _ in range(r.randrange(1, 5)))


def grown(r, depth):
    """A structure: ("p", text), ("div", parts), ("list", ordered, items), ("table", rows of (text, rowspan)), ("off", part)."""
    kind = r.choice(["p", "p", "div", "list", "table", "off"] if depth else ["p"])
    if kind == "p":
        return ("p", sentence(r))
    if kind == "off":
        return ("off", r.choice(HIDE)[0], grown(r, depth - 1))
    if kind == "div":
        return ("div", [grown(r, depth - 1) for _ in range(r.randrange(1, 4))])
    if kind == "list":
        return ("list", r.random() < 0.5, [(sentence(r), [grown(r, depth - 1) for _ in range(r.randrange(2))]) for _ in range(r.randrange(1, 4))])
    return ("table", [[(sentence(r), r.choice([1, 1, 2]), r.choice([1, 1, 1, 2])) for _ in range(r.randrange(1, 4))] for _ in range(r.randrange(1, 4))])


def written(x, r):
    end = lambda tag: r.choice([f"</{tag}>", ""])  # noqa: E731  ends that are implied are left out at times
    if x[0] == "p":
        return f"<p class=v>{r.choice([' ', ''])}{x[1].replace(' ', r.choice([' ', '  ', chr(10)]))}</p>"
    if x[0] == "off":
        return f"<div {x[1]}>{written(x[2], r)}</div>"
    if x[0] == "div":
        return "<div>" + "".join(written(c, r) for c in x[1]) + "</div>"
    if x[0] == "list":
        tag = "ol" if x[1] else "ul"
        return f"<{tag}>" + "".join(f"<li>{t}{''.join(written(c, r) for c in more)}{end('li')}" for t, more in x[2]) + f"</{tag}>"
    return "<table>" + "".join("<tr>" + "".join(f"<td rowspan={d} colspan={a}>{t}{end('td')}" for t, d, a in row) + end("tr") for row in x[1]) + "</table>"


def lines_of(x):
    """Lines, None where a blank line is due."""
    if x[0] == "p":
        return [None, x[1], None]
    if x[0] == "off":
        return []
    if x[0] == "div":
        return [line for c in x[1] for line in lines_of(c)]
    if x[0] == "list":
        out = [None]
        for k, (t, more) in enumerate(x[2], 1):
            mark = f"{k}. " if x[1] else "- "
            inner = [t]
            for c in more:
                part = lines_of(c)
                inner += part[1:-1] if c[0] == "list" else part
            inner = settled(inner)
            out += [mark + inner[0]] + [" " * len(mark) + s if s else s for s in inner[1:]]
        return [*out, None]
    grid, rows = {}, []
    for i, row in enumerate(x[1]):
        at = 0
        rows.append([])
        for t, down, across in row:
            while (i, at) in grid:
                at += 1
            for di in range(1, down):
                for dj in range(across):
                    grid[i + di, at + dj] = True
            rows[-1].append((at, across, t))
            at += across
    used = sorted({at for row in rows for at, _, _ in row})
    width = {c: max([len(t) for row in rows for at, a, t in row if at == c and not any(c < u < c + a for u in used)], default=0) for c in used}
    for row in rows:
        for at, a, t in row:
            inside = [u for u in used if at <= u < at + a]
            if len(inside) > 1:
                width[inside[-1]] = max(width[inside[-1]], len(t) - sum(width[u] + 2 for u in inside[:-1]))
    out = [None]
    for row in rows:
        line = ""
        for at, _, t in row:
            line = line.ljust(sum(width[u] + 2 for u in used if u < at and width[u])) + t
        out.append(line)
    return [*out, None]


def settled(lines):
    out = []
    for x in lines:
        if x is not None:
            out.append(x)
        elif out and out[-1] != "":
            out.append("")
    while out and out[-1] == "":
        out.pop()
    return out


def test_against_reference():
    r = random.Random(12)
    for _ in range(600):
        parts = [grown(r, 3) for _ in range(3)]
        page = "<!DOCTYPE html><head><title>t</title>" + SHEET + "</head><body>" + "".join(written(p, r) for p in parts) + "<script>var a = '<p>no</p>'</script>"
        assert html_text.render(page) == "\n".join(settled([x for p in parts for x in lines_of(p)])), page


@pytest.mark.parametrize(
    "page,text",
    [
        ("<style>.h{display:none}</style><div class=h style='display:block'>a</div>", "a"),
        ("<style>.h{display:none!important}</style><div class=h style='display:block'>a</div>b", "b"),
        ("<style>@media print{.n{display:none}} @media screen and (min-width:600px){.m{display:none}}</style><p class=n>a<p class=m>b", "a"),
        ("<style media=print>p{display:none}</style><p>a", "a"),
        ("<style>div.x{display:none} p.y,b{visibility:hidden}</style><div class=x>a</div><p class=x>b</p><p class=y>c<i style='visibility:visible'>d</i>", "b\n\nd"),
        ("<style>#a .b{display:none} .b{display:block}</style><div id=a><i><u class=b>x</u></i></div><span class=b>y</span>z", "y\nz"),
        ("<style>@supports (display:grid){.s{display:none}} @font-face{x:y} @keyframes k{0%{display:none}} .k{content:'}{'; display:none}</style><p class=s>a<p class=k>b<p>c", "c"),
        ("<table><tr><td rowspan=2>a<td>b<tr><td>c</table>", "a  b\n   c"),
        ("<table><tr><th colspan=2>long header<tr><td>c<td>d</table>", "long header\nc  d"),
        ("<table><tfoot><tr><td>z</tfoot><tr><td>b<thead><tr><td>a</table>", "a\nb\nz"),
        ("<div>" * 200 + "<div hidden>secret</div>tail", "tail"),
        ("<div>" * 5000 + "<div style='display:none'>secret</div>tail</p>" + "</div>" * 9000 + "end", "tail\nend"),
        ("<ul><li>" * 5000 + "x", "- " * 32 + "x"),
        ("<style>li{display:inline}</style><ul><li>a</li> <li>b</li></ul>", "a b"),
        ("<div style='display:table'><div style='display:table-row'><i style='display:table-cell'>a</i><i style='display:table-cell'>b</i></div></div>", "a  b"),
        ("<svg><title>t</title><text>s</text></svg> <math><mi>m</mi></math> <object>o</object>", "s m o"),
        ("<details><summary>s</summary>a</details><details open><summary>t</summary>b</details>", "s\nt\nb"),
    ],
)
def test_cascade_and_layout(page, text):
    assert html_text.render(page) == text


def test_tables_of_pages(spark):
    schema = "page_id long, html string, text string, n_lines string"
    assert html_text.extract_text(spark.createDataFrame([], schema)).count() == 0
    flat = "word " * 400_000
    rows = [(1, "<p>a", "t", "n"), (1, "<p>a", "t", "n"), (2, flat, "t", "n"), (None, None, None, None), (3, "", "", "")]
    got = sorted(((r["page_id"] or 0), r["text"], r["n_lines"]) for r in html_text.extract_text(spark.createDataFrame(rows, schema)).collect())
    assert got == [(0, "", 0), (1, "a", 1), (1, "a", 1), (2, flat.strip(), 1), (3, "", 0)]
