"""A scanner for HTML that reads every character a bounded number of times, whatever the page."""

from __future__ import annotations

import re
from collections.abc import Iterator

#: fixed values: elements whose content is not markup
RAW = frozenset("script style textarea title noscript iframe xmp noembed noframes".split())
#: the ASCII letters only: lower-casing others can move places
LOWER = {c: c + 32 for c in range(65, 91)}

_NAME = re.compile(r"[a-zA-Z][^\s/>]*")
_STOP = re.compile(r"""[>"']""")
#: what ends a raw element, in ASCII letters of either case
_CLOSE = {tag: re.compile(f"</{tag}(?=[ \\t\\n\\f\\r/>]|\\Z)", re.I | re.A) for tag in RAW}


class _Ends:
    """``str.find`` from rising places that remembers a failure, so that no missing string is sought twice."""

    def __init__(self, text: str):
        self.text, self.none, self.loose = text, set(), False

    def find(self, what: str, at: int) -> int:
        if what in self.none:
            return -1
        found = self.text.find(what, at)
        if found < 0:
            self.none.add(what)
        return found


def lowered(name: str) -> str:
    return name.lower() if name.isascii() else name.translate(LOWER)


def _tag_end(html: str, at: int, ends: _Ends) -> int:
    """The place of the ``>`` that closes a tag; quoted values may hold others. A quote that never ends is no quote.

    Where quotes would hide every ``>`` to the end of the page, they count for nothing from there on.
    """
    start = at
    while True:
        m = None if ends.loose else _STOP.search(html, at)
        if m is None:
            ends.loose = True
            return html.find(">", start)
        if m[0] == ">":
            return m.start()
        at = m.end()
        before = m.start() - 1
        while html[before].isspace():
            before -= 1
        if html[before] == "=":
            close = ends.find(m[0], at)
            if close >= 0:
                at = close + 1


def tokens(html: str) -> Iterator[tuple[str, str, str]]:
    """``("text", characters, "")``, ``("open", tag, attributes)``, ``("close", tag, "")`` and ``("raw", tag, content)`` in order.

    Comments and declarations are left out. What a page leaves open, its end closes: an unclosed comment, raw element or
    tag takes the rest.
    """
    at, end, ends = 0, len(html), _Ends(html)
    while at < end:
        lt = html.find("<", at)
        if lt < 0:
            yield "text", html[at:], ""
            return
        if lt > at:
            yield "text", html[at:lt], ""
        nxt = html[lt + 1 : lt + 2]
        if nxt == "!" or nxt == "?":
            comment = html.startswith("<!--", lt)
            stop = ends.find("-->", lt + 2) if comment else html.find(">", lt)
            if stop < 0:
                return
            at = stop + (3 if comment else 1)
            continue
        closing = nxt == "/"
        m = _NAME.match(html, lt + 1 + closing)
        if m is None:
            yield "text", "<", ""
            at = lt + 1
            continue
        stop = m.end() if html.startswith(">", m.end()) else _tag_end(html, m.end(), ends)
        if stop < 0:
            return
        tag, at = lowered(m[0]), stop + 1
        if closing:
            yield "close", tag, ""
            continue
        yield "open", tag, html[m.end() : stop]
        if tag in RAW:
            close = _CLOSE[tag].search(html, at)
            yield "raw", tag, html[at : close.start()] if close else html[at:]
            if close is None:
                return
            gt = html.find(">", close.start())
            if gt < 0:
                return
            at = gt + 1
