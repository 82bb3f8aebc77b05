"""Labelled pages for the block field: crawled pages labelled by their documents, and pages set from templates.

``python -m litspark.llm.html_training SF_DIR`` fits the field on at most
``SAMPLE_PAGES`` crawled and as many set pages and writes its weights.
"""

from __future__ import annotations

import random
import re
import sys

from litspark.llm.html_blocks import Block, leaf_blocks
from litspark.llm.html_crf import Field

SAMPLE_PAGES = 1000
MARK = "␂"


def label_by_document(page: str, document: str) -> tuple[list[Block], list[int]]:
    """Blocks of a page and labels: main are the blocks that spell the document in order; headings are taken last."""
    blocks = leaf_blocks(page)
    want, labels, at = " ".join(document.split()), [0] * len(blocks), 0
    for i, b in enumerate(blocks):
        if b.path and b.path[-1][0] == "h1":
            continue
        if want.startswith(b.text, at):
            labels[i] = 1
            at += len(b.text) + 1
    return blocks, labels


def set_page(rng: random.Random, texts: list[str]) -> tuple[list[Block], list[int]]:
    """A page set from random templates; main blocks carry a mark that is taken off again."""
    pick = lambda: " ".join(rng.choice(texts).split()[: rng.choice((rng.randint(1, 4), rng.randint(4, 60)))]) or "text"
    short = lambda: " ".join(rng.choice(texts).split()[: rng.randint(1, 4)]) or "x"
    esc = lambda s: s.replace("&", "&amp;").replace("<", "&lt;")
    main = lambda: esc(MARK + pick())
    links = lambda n: "<ul>" + "".join(f'<li><a href="/{i}">{esc(short())}</a></li>' for i in range(n)) + "</ul>"

    def named(*names: str) -> str:
        return rng.choice((f'class="{rng.choice(names)}"', f'id="{rng.choice(names)}"', f'class="box {rng.choice(names)}-block"'))

    def extra() -> str:
        kind = rng.randrange(9)
        if kind == 0:
            return f'<div {named("ad", "ads", "advert", "advertisement", "sponsor", "sponsored", "promo", "banner")}>{esc(pick())}</div>'
        if kind == 1:
            return f'<aside {named("sidebar", "related", "widget", "rail")}><h3>{esc(short())}</h3>{links(3)}<p>{esc(pick())}</p></aside>'
        if kind == 2:
            return f'<div {named("notice", "cookie", "consent", "alert", "popup", "modal", "gdpr", "newsletter", "subscribe")}><p>{esc(pick())}</p><button>{esc(short())}</button></div>'
        if kind == 3:
            return f'<form action="/s"><label>{esc(short())}</label><input name="q"><p>{esc(pick())}</p><button>{esc(short())}</button></form>'
        if kind == 4:
            return f'<div {named("share", "social", "tags", "meta", "breadcrumb", "breadcrumbs", "pagination", "toolbar")}>{links(4)}</div>'
        if kind == 5:
            return f'<aside>{esc(pick())}</aside>'
        if kind == 6:
            return f'<div {named("related", "recommended", "more", "popular", "trending")}><h3>{esc(short())}</h3>{links(4)}</div>'
        if kind == 7:
            return f'<section {named("ad", "promo", "newsletter", "notice")}><p>{esc(pick())}</p></section>'
        return ""

    def paragraph() -> str:
        kind = rng.randrange(12)
        if kind == 0:
            return f"<ul><li>{main()}</li><li>{main()}</li></ul>"
        if kind == 1:
            return f"<blockquote><p>{main()}</p></blockquote>"
        if kind == 2:
            return f"<h2>{main()}</h2><p>{main()}</p>"
        if kind == 3:
            return f"<table><tr><td>{main()}</td><td>{main()}</td></tr></table>"
        if kind == 4:
            return f"<p><b>{main()}<br><p>{main()}</p>"
        if kind == 5:
            return f'<p>{main()} <a href="/x">{esc(short())}</a> {esc(short())}.'
        if kind == 6:
            return f"<pre>{main()}</pre>"
        return f"<p>{main()}</p>"

    def comment() -> str:
        return f'<div {named("comment", "reply")}><b>{esc(short())}</b><p>{esc(pick())}</p></div>'

    comments = lambda: f'<{(t := rng.choice(("section", "div", "ol")))} {named("comments", "discussion", "replies", "comment-list", "reader-comments")}><h2>{esc(short())}</h2>' + "".join(comment() for _ in range(rng.randint(1, 4))) + f"</{t}>"
    title = pick()
    inner = [f"<h1>{esc(title)}</h1>"] if rng.random() < 0.9 else []
    if rng.random() < 0.3:
        inner = ["<header>" + "".join(inner) + f"<p>{esc(short())}</p></header>"]
    for _ in range(rng.choice((1, 1, rng.randint(1, 12)))):
        inner.append(paragraph())
        if rng.random() < 0.15:
            inner.append(extra())
    if rng.random() < 0.2:
        inner.append(comments())
    if rng.random() < 0.15:
        inner.append(f"<footer><p>{esc(pick())}</p></footer>")
    body = "".join(inner)
    wrap = rng.randrange(4)
    body = (f"<article>{body}</article>", f"<main><article>{body}</article></main>", f'<main {named("content", "post", "entry")}>{body}</main>', f'<div {named("content", "article", "post", "entry", "story")}>{body}</div>')[wrap]
    head = rng.choice((f"<nav>{links(6)}</nav>", f'<header><a href="/">{esc(short())}</a><nav>{links(4)}</nav></header>', f'<div {named("menu", "navbar", "nav", "header", "topbar")}>{links(5)}</div>', f"<header><p>{esc(pick())}</p></header>"))
    foot = rng.choice((f"<footer>&copy; {esc(pick())}</footer>", f'<footer><p>{esc(pick())}</p>{links(3)}</footer>', f'<div {named("footer", "copyright", "bottom")}>{esc(pick())}</div>', ""))
    page = f"<html><head><title>{esc(title)}</title></head><body>{head}{extra()}{extra()}{body}{extra()}{comments() if rng.random() < 0.4 else ''}{extra()}{foot}</body></html>"
    blocks = leaf_blocks(page)
    labels = [int(MARK in b.text) for b in blocks]
    for b in blocks:
        b.text = re.sub(MARK, "", b.text)
    return blocks, labels


def labelled_pages(sf_dir: str, limit: int = SAMPLE_PAGES, seed: int = 5) -> list[tuple[list[Block], list[int]]]:
    """At most ``limit`` crawled pages (smallest page_id first) and as many set ones."""
    import pyarrow.parquet as pq

    documents = dict(zip(*(pq.read_table(f"{sf_dir}/documents.parquet").column(c).to_pylist() for c in ("doc_id", "text"))))
    pages = sorted(pq.read_table(f"{sf_dir}/pages.parquet").to_pylist(), key=lambda r: r["page_id"])[:limit]
    out = []
    for row in pages:
        found = re.search(r"/(?:en|fr|de|es)/([0-9]+)", row["url"])
        if found and int(found[1]) in documents:
            out.append(label_by_document(row["html"], documents[int(found[1])]))
    rng, texts = random.Random(seed), [t for t in documents.values() if t]
    return out + [set_page(rng, texts) for _ in range(limit)]


if __name__ == "__main__":
    Field().fit(labelled_pages(sys.argv[1])).save()
