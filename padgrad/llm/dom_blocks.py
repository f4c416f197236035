"""DOM leaf blocks of a page: runs of text between block borders, with their ancestors."""

from __future__ import annotations

import html
import re
from typing import NamedTuple

VOID = frozenset("area base br col embed hr img input link meta source track wbr param".split())
#: Elements whose content is no text of the page.
UNSEEN = frozenset("script style title template noscript svg iframe object head".split())
RAW = frozenset("script style title textarea iframe noscript".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var".split())
#: What a page head may hold; any other element, or text, ends a head that was left open.
HEAD = frozenset("base link meta title style script noscript template bgsound basefont noframes head".split())
#: An open element of the first kind is closed by the start of any of the second.
CLOSED_BY = {
    "p": frozenset("p div ul ol li table h1 h2 h3 h4 h5 h6 section article aside header footer nav form blockquote pre main figure hr dl address fieldset".split()),
    "li": frozenset(["li"]), "option": frozenset(["option"]), "td": frozenset("td th tr".split()), "th": frozenset("td th tr".split()),
    "tr": frozenset(["tr"]), "dt": frozenset("dt dd".split()), "dd": frozenset("dt dd".split()),
}
_MARKUP = re.compile(r"""<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']+|"[^"]*"|'[^']*')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>|<[!?][^>]*>|<[/a-zA-Z!?][^>]*\Z""", re.S)
_NAMES = re.compile(r"""\b(class|id|role|itemprop)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_PART = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")
_ENDS = {t: re.compile(rf"</{t}\b[^>]*(?:>|\Z)", re.I) for t in RAW}


class Block(NamedTuple):
    text: str  # one space for each run of white space, trimmed
    path: tuple  # of (tag, names) from the root
    linked: int  # characters of text in links


_names_of: dict[str, tuple] = {}


def names(attributes: str) -> tuple:
    """Lower-cased parts of class, id and role names."""
    if attributes not in _names_of:
        if len(_names_of) > 20_000:
            _names_of.clear()
        found = []
        for m in _NAMES.finditer(attributes):
            found += [p.lower() for p in _PART.findall(m[2] or m[3] or m[4] or "")]
        _names_of[attributes] = tuple(dict.fromkeys(found))
    return _names_of[attributes]


def leaf_blocks(page: str | None) -> list[Block]:
    """All non-empty leaf blocks in page order."""
    page = page or ""
    blocks: list[Block] = []
    stack: list[tuple] = []
    parts: list[str] = []
    linked = unseen = links = at = 0

    def border():
        nonlocal linked
        if parts:
            text = " ".join(html.unescape("".join(parts)).split())
            if text:
                blocks.append(Block(text, tuple(stack), linked))
            parts.clear()
        linked = 0

    def end_head():
        for k in range(len(stack) - 1, -1, -1):
            if stack[k][0] == "head":
                leave(k)
                break

    def leave(depth):
        nonlocal unseen, links
        for tag, _ in stack[depth:]:
            unseen -= tag in UNSEEN
            links -= tag == "a"
        del stack[depth:]

    size = len(page)
    while at < size:
        m = _MARKUP.search(page, at)
        upto = m.start() if m else size
        if unseen and stack[-1][0] == "head" and page[at:upto].strip():
            leave(len(stack) - 1)
        if upto > at and not unseen:
            parts.append(page[at:upto])
            if links:
                linked += upto - at
        if not m:
            break
        at = m.end()
        name = m[2] or m[5]
        if not name:
            continue
        tag = name.lower()
        if tag not in INLINE:
            border()
        closing = m[1] or m[4]
        if unseen and (tag == "body" if closing else tag not in HEAD):
            end_head()
        if closing:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    leave(k)
                    break
            continue
        if tag not in INLINE:
            for k in range(len(stack) - 1, -1, -1):
                if tag in CLOSED_BY.get(stack[k][0], ()):
                    leave(k)
                    break
                if stack[k][0] not in INLINE and stack[k][0] != "p":
                    break
        attributes = (m[3] if m[2] else m[6]) or ""
        if tag in RAW:
            end = _ENDS[tag].search(page, at)
            at = end.end() if end else size
        elif tag not in VOID and not attributes.endswith("/"):
            stack.append((tag, names(attributes) if "=" in attributes else ()))
            unseen += tag in UNSEEN
            links += tag == "a"
    border()
    return blocks
