"""Leaf blocks of a page in page order, from markup that may be broken."""

from __future__ import annotations

import html
import re
from dataclasses import dataclass

# fixed values: HTML element kinds
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SILENT = frozenset("script style template noscript iframe object svg math canvas audio video select textarea button datalist head title".split())
HEAD = frozenset("base basefont bgsound head html link meta noframes noscript script style template title".split())
RAW = frozenset("script style textarea title".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
IMPLIED = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}

MARKUP = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)", re.S)
NAMES = re.compile(r"\b(?:class|id|role|itemprop)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
PARTS = re.compile(r"[A-Za-z]+")


@dataclass
class Block:
    path: tuple[str, ...]
    text: str
    linked: int  # characters inside links


def labels(tag: str, attributes: str) -> tuple[str, ...]:
    """The tag and the words of its class, id and role, as parts of a path."""
    found = [tag]
    if attributes:
        for groups in NAMES.findall(attributes):
            found += [f".{p.lower()}" for p in PARTS.findall("".join(groups))]
    return tuple(found)


def blocks(page: str | None) -> list[Block]:
    """Blocks with text: references decoded, white space made single spaces, ends trimmed."""
    out: list[Block] = []
    stack: list[tuple[str, tuple[str, ...]]] = []
    text: list[str] = []
    linked = silent = links = 0

    def flush() -> None:
        nonlocal linked
        if text:
            whole = " ".join("".join(text).split())
            if whole:
                out.append(Block(tuple(x for tag, parts in stack if tag not in INLINE for x in parts), whole, linked))
            text.clear()
        linked = 0

    def pop_to(depth: int) -> None:
        nonlocal silent, links
        if any(tag not in INLINE for tag, _ in stack[depth:]):
            flush()
        for tag, _ in stack[depth:]:
            silent -= tag in SILENT
            links -= tag == "a"
        del stack[depth:]

    def find(tags: set[str] | frozenset[str], stop: set[str] | frozenset[str]) -> int | None:
        for depth in range(len(stack) - 1, -1, -1):
            if stack[depth][0] in tags:
                return depth
            if stack[depth][0] in stop:
                return None
        return None

    page = page or ""
    at, n = 0, len(page)
    while at < n:
        found = MARKUP.search(page, at)
        start = found.start() if found else n
        if start > at and silent and stack[-1][0] == "head" and html.unescape(page[at:start]).strip():
            pop_to(len(stack) - 1)
        if start > at and not silent:
            piece = html.unescape(page[at:start])
            text.append(piece)
            if links:
                linked += len(piece.strip())
        if not found:
            break
        at = found.end()
        tag = (found[2] or "").lower()
        if not tag:
            continue
        if found[1]:
            depth = find({tag}, frozenset() if tag in INLINE or tag in CLOSES_P or tag == "body" else {"table"})
            if depth is not None:
                pop_to(depth)
            elif tag == "p":
                flush()
            continue
        if tag not in HEAD and stack and stack[-1][0] == "head":
            pop_to(len(stack) - 1)
        if tag in VOID:
            if tag in INLINE:
                if not silent and tag in ("br", "img", "wbr"):
                    text.append("" if tag == "wbr" else " ")
            else:
                flush()
            continue
        if tag in CLOSES_P and (depth := find({"p"}, {"table", "button", "article", "section", "div"})) is not None:
            pop_to(depth)
        if tag in IMPLIED and (depth := find(*IMPLIED[tag])) is not None:
            pop_to(depth)
        if tag == "body" and (depth := find({"head"}, frozenset())) is not None:
            pop_to(depth)
        if tag not in INLINE and tag not in SILENT:
            flush()
        if tag in RAW:
            end = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
            at = end.end() if end else n
            continue
        stack.append((tag, labels(tag, found[3])))
        silent += tag in SILENT
        links += tag == "a"
    flush()
    return out
