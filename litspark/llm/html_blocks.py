"""Leaf blocks of a page: text runs between block-level tags, with their open elements."""

from __future__ import annotations

import html
import re
from dataclasses import dataclass, field

# Element names of HTML by their role in cutting text into blocks.
INLINE = frozenset("a abbr b bdi bdo cite code data dfn em font i kbd label mark q s samp small span strong sub sup time tt u var wbr ins del big acronym".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template svg math iframe object textarea select".split())
CLOSES = {
    "p": frozenset(("p",)), "li": frozenset(("li", "p")), "dt": frozenset(("dt", "dd", "p")), "dd": frozenset(("dt", "dd", "p")),
    "tr": frozenset(("tr", "td", "th", "p")), "td": frozenset(("td", "th", "p")), "th": frozenset(("td", "th", "p")), "option": frozenset(("option",)),
}
#: An element that is opened inside one of these does not close what lies outside it.
SCOPES = frozenset("article aside body div dl footer form header html main nav ol section table ul blockquote figure td th fieldset".split())
#: Block tags that end an open paragraph.
ENDS_P = frozenset("address article aside blockquote div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())

#: A well-formed tag; possessive, so that a match that fails has read each character once.
_TAG = re.compile(r"<(/?)([A-Za-z][^\s/>]*+)((?:[\s/]++[^\s\"'<>/=]++(?:=(?:\"[^\"<>]*+\"|'[^'<>]*+'|[^\s\"'<>=`]++))?+)*+)[\s/]*+>")
_OPENED = re.compile(r"<(/?)([A-Za-z][^\s/>]*+)")
_GAP = re.compile(r"[\s/]*+")
_KEY = re.compile(r"[^\s/>][^\s/>=]*+")
_SIGN = re.compile(r"\s*+=\s*+")
_BARE = re.compile(r"[^\s>]*+")
_ATTR = re.compile(r"([^\s\"'<>/=]++)=(?:\"([^\"]*+)\"|'([^']*+)'|([^\s>]++))")
#: Elements nested deeper than this are not told apart; their text stays.
DEPTH = 256
_NAME_PART = re.compile(r"[A-Za-z]+")


@dataclass
class Block:
    """A run of text, its open elements (tag, words of class, id and role) and how much of it is link text."""

    text: str
    path: tuple[tuple[str, tuple[str, ...]], ...]
    linked: int = 0
    title: str = ""


@dataclass
class _Page:
    stack: list[tuple[str, tuple[str, ...]]] = field(default_factory=list)
    parts: list[str] = field(default_factory=list)
    linked: int = 0
    in_link: int = 0
    deeper: int = 0
    blocks: list[Block] = field(default_factory=list)

    def text(self, raw: str) -> None:
        if raw:
            self.parts.append(raw)
            if self.in_link:
                self.linked += len(raw)

    def flush(self) -> None:
        text = " ".join(html.unescape("".join(self.parts)).split())
        if text:
            path = tuple(e for e in self.stack if e[0] not in INLINE)
            self.blocks.append(Block(text, path, min(self.linked, len(text))))
        self.parts, self.linked = [], 0

    def close(self, name: str) -> None:
        if name == "a":
            self.in_link = max(0, self.in_link - 1)
        if name not in INLINE:
            self.flush()
        if self.deeper:
            self.deeper -= 1
            return
        for i in range(len(self.stack) - 1, -1, -1):
            if self.stack[i][0] == name:
                del self.stack[i:]
                break
            if name in INLINE and self.stack[i][0] not in INLINE:
                break

    def open(self, name: str, attributes: list[tuple[str, str]], closed: bool) -> None:
        if name not in INLINE:
            self.flush()
            self.in_link = 0
            closing = CLOSES.get(name, frozenset()) | (frozenset(("p",)) if name in ENDS_P else frozenset())
            for i in range(len(self.stack) - 1 if closing and not self.deeper else -1, -1, -1):
                if self.stack[i][0] in closing:
                    del self.stack[i:]
                elif self.stack[i][0] in SCOPES:
                    break
        if name == "a":
            self.in_link += 1
        if name in VOID or closed:
            return
        if len(self.stack) >= DEPTH:
            self.deeper += 1
            return
        named = [w.lower() for key, value in attributes if key.lower() in ("class", "id", "role") for w in _NAME_PART.findall(value)]
        self.stack.append((name, tuple(dict.fromkeys(named))))


class _Finder:
    """Searches of one page that remember what is not there any more, so that all of them together are linear."""

    def __init__(self, page: str):
        self.page = page
        self.absent: set[str] = set()

    def find(self, what: str, at: int) -> int:
        if what in self.absent:
            return -1
        found = self.page.find(what, at)
        if found < 0:
            self.absent.add(what)
        return found

    def raw_end(self, name: str, at: int) -> tuple[int, int] | None:
        """Where the raw element's text ends and where its end tag does."""
        key = f"</{name}"
        if key in self.absent:
            return None
        m = re.compile(rf"</{re.escape(name)}(?=[\s/>])[^<>]*+>?", re.I).search(self.page, at)
        if not m:
            self.absent.add(key)
            return None
        return m.start(), m.end()

    def attributes(self, at: int) -> tuple[list[tuple[str, str]], int] | None:
        """Attributes of a tag that is open at ``at`` and the place behind its ``>``; None if the page ends before.

        Unquoted values end at white space or ``>``, whatever quotes they hold.
        A quoted value that runs over a ``>`` to a quote that nothing of a tag
        follows, or to none, has lost its own quote: it ends at its first ``>``.
        """
        page, out = self.page, []
        while True:
            at = _GAP.match(page, at).end()
            if at >= len(page):
                return None
            if page[at] == ">":
                return out, at + 1
            m = _KEY.match(page, at)
            at, value = m.end(), ""
            sign = _SIGN.match(page, at)
            if sign:
                at = sign.end()
                quote = page[at : at + 1]
                if quote in ('"', "'") and quote:
                    end, stop = self.find(quote, at + 1), -1
                    if end < 0:
                        stop = self.find(">", at + 1)
                    elif page[end + 1 : end + 2] not in ("", ">", "/") and not page[end + 1].isspace():
                        stop = page.find(">", at + 1, end)
                    if end < 0 and stop < 0:
                        return None
                    value = page[at + 1 : end if stop < 0 else stop]
                    at = end + 1 if stop < 0 else stop
                else:
                    at = (bare := _BARE.match(page, at)).end()
                    value = bare.group()
            out.append((m.group(), value))


def leaf_blocks(page: str | None) -> list[Block]:
    """Blocks of a page in order; text of scripts, styles and other raw elements is no block.

    Any input is accepted, in time linear in its length.  What a page leaves open
    is read as browsers do: a comment, script or style to the end, a tag cut off
    by the end of the page is dropped; other elements stay open.
    """
    if not page:
        return []
    p, seek, at, title = _Page(), _Finder(page), 0, ""
    while True:
        start = seek.find("<", at)
        if start < 0:
            p.text(page[at:])
            break
        p.text(page[at:start])
        m = _TAG.match(page, start)
        if m:
            ending, name, inside, at = m.group(1), m.group(2).lower(), m.group(3), m.end()
            closed = page[at - 2] == "/"
            attributes = [(key, "".join(values)) for key, *values in _ATTR.findall(inside)] if inside and not ending else []
        elif m := _OPENED.match(page, start):
            ending, name = m.group(1), m.group(2).lower()
            read = seek.attributes(m.end())
            if read is None:
                break
            attributes, at = read
            closed = page[at - 2] == "/"
        else:
            at = _markup_end(seek, start)
            if at < 0:
                break
            if at == start:  # a bare "<"
                p.text("<")
                at += 1
            continue
        if ending:
            p.close(name)
            continue
        if name in RAW or name == "title":
            ends = None if closed else seek.raw_end(name, at)
            if name == "title":
                title = " ".join(html.unescape(page[at : ends[0]]).split()) if ends else title
            elif name not in INLINE:
                p.flush()
            if ends:
                at = ends[1]
            elif name in ("script", "style") and not closed:
                break
            continue
        p.open(name, attributes, closed)
    p.flush()
    for b in p.blocks:
        b.title = title
    return p.blocks


def _markup_end(seek: _Finder, start: int) -> int:
    """Where a comment, declaration or odd end tag at ``start`` ends; ``start`` if it is text, -1 if the page ends in it."""
    page = seek.page
    if page.startswith("<!--", start):
        if page.startswith((">", "->"), start + 4):
            return page.index(">", start) + 1
        end = seek.find("-->", start + 4)
        return end + 3 if end >= 0 else -1
    if page.startswith("<![CDATA[", start):
        end = seek.find("]]>", start)
        if end >= 0:
            return end + 3
    if page.startswith(("<!", "<?", "</"), start) and start + 2 < len(page):
        end = seek.find(">", start)
        return end + 1 if end >= 0 else -1
    return start
