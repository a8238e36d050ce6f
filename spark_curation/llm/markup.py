"""A scanner of tag soup whose time grows with the page, whatever the page holds."""

from __future__ import annotations

import re
from collections.abc import Iterator

_NAME = re.compile(r"/?[A-Za-z][^\s/>]*")
_STOP = re.compile(r">|=\s*[\"']")
#: Elements that run to the end of the page if they are not closed, once they are dropped.
RAW = frozenset("script style title textarea".split())
ATTRIBUTE = re.compile(r"([^\s=\"'/>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")


class Scanner:
    """Text and tags of a page in order; comments, declarations and the elements in ``dropped`` are left out."""

    def __init__(self, page: str, dropped: frozenset[str]):
        self.page = page
        self._dropped = dropped
        self._last = {q: page.rfind(q) for q in "\"'"}
        self._quotes = True
        self._ends: dict[str, dict[int, int]] = {}

    def __iter__(self) -> Iterator[tuple[str, str, str]]:
        """(text before a tag, its name in lower case, with a slash before it if it closes, what else the tag holds).

        A dropped element comes as its opening tag, with its content in place of attributes. The last name is empty.
        """
        page, at, seen = self.page, 0, 0  # text before ``seen`` has been given out
        while (at := page.find("<", at)) >= 0:
            kind = page[at + 1 : at + 2]
            if kind in ("!", "?"):
                if page.startswith("<!--", at):
                    ends = [e for e in (page.find("-->", at + 2), page.find("--!>", at + 4)) if e >= 0]
                    end = page.index(">", min(ends)) + 1 if ends else len(page)
                else:
                    end = page.find(">", at) + 1
                if not end:
                    break
                if at > seen:
                    yield page[seen:at], "!", ""
                at = seen = end
                continue
            m = _NAME.match(page, at + 1)
            if m is None:
                at += 1
                continue
            end = self._tag_end(m.end())
            if end < 0:
                break
            name = m[0].lower()
            after = self._skip(name, at, end) if name in self._dropped else end
            yield page[seen:at], name, page[end:after] if after > end else page[m.end() : end - 1]
            at = seen = after
        yield page[seen:], "", ""

    def _tag_end(self, at: int) -> int:
        """Where the tag whose name ends at ``at`` ends: after the first ``>`` outside quoted values; -1 if nowhere."""
        page, begin = self.page, at
        while self._quotes and (m := _STOP.search(page, at)) is not None:
            if m[0] == ">":
                return m.end()
            quote = m[0][-1]
            at = page.index(quote, m.end()) + 1 if self._last[quote] >= m.end() else m.end()
        self._quotes = False  # quotes are out of step: from here on they mean nothing
        return page.find(">", begin) + 1 or -1

    def _skip(self, tag: str, start: int, end: int) -> int:
        """Where an element that is dropped ends; one that stays open is a mere tag, or runs to the end of the page."""
        if tag not in self._ends:
            stack: list[int] = []
            ends = self._ends[tag] = {}
            for m in re.finditer(rf"<(/?){re.escape(tag)}(?=[\s/>])([^<>]*)>?", self.page, re.I):
                if m[1]:
                    if stack:
                        ends[stack.pop()] = m.end()
                elif m[2].endswith("/") and tag not in RAW:
                    ends[m.start()] = m.end()
                elif tag not in RAW or not stack:
                    stack.append(m.start())
        return self._ends[tag].get(start, len(self.page) if tag in RAW else end)
