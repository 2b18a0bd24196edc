"""HTML to a sequence of text blocks, each with the path of tags it stands under."""

from __future__ import annotations

import html
import re
from bisect import bisect_left, bisect_right
from dataclasses import dataclass

#: Fixed sets of tags.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe noembed noframes xmp".split())
BLOCK = frozenset(
    "address article aside blockquote body button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre search section select summary table tbody td tfoot th thead tr ul".split()
)
#: A tag that opens ends an open one of these, if no tag of the second set stands between.
ENDS = {tag: (frozenset("p".split()), frozenset("td th li dd blockquote button object".split())) for tag in BLOCK - {"body", "html", "head", "option", "optgroup"}}
ENDS |= {"li": (frozenset("li p".split()), frozenset("ul ol menu".split()))}
ENDS |= {t: (frozenset("dt dd p".split()), frozenset("dl".split())) for t in ("dt", "dd")}
ENDS |= {t: (frozenset("td th p".split()), frozenset("table".split())) for t in ("td", "th")}
ENDS |= {"tr": (frozenset("tr td th p".split()), frozenset("table".split()))}
ENDS |= {t: (frozenset("option p".split()), frozenset("select".split())) for t in ("option", "optgroup")}

ATTRIBUTE = re.compile(r"""(?:class|id|role)\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+)""", re.I)
HREF = re.compile(r"(?:^|\s)href\s*=", re.I)
NAME = re.compile(r"[a-z]+")
OPENING = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
_SPECIAL = re.compile(r"""[>"']""")


class Place:
    """An open element: its tag, its attribute words, and whether it lies in a link or in the head."""

    __slots__ = ("tag", "words", "above", "linked", "hidden", "slots")

    def __init__(self, tag: str, words: tuple[str, ...], above: Place | None, link: bool):
        self.tag, self.words, self.above = tag, words, above
        self.linked = link or (above is not None and above.linked)
        self.hidden = tag == "head" or (above is not None and above.hidden)
        #: For readers that keep what they find of an element and all above it.
        self.slots: int | None = None


@dataclass
class Block:
    """A block's text, the innermost element it stands in, and how much of it is in links."""

    text: str
    place: Place | None
    linked: float = 0.0

    def _line(self) -> list[Place]:
        out, at = [], self.place
        while at is not None:
            out.append(at)
            at = at.above
        return out[::-1]

    @property
    def path(self) -> tuple[str, ...]:
        """Tags from the outermost element in."""
        return tuple(p.tag for p in self._line())

    @property
    def words(self) -> tuple[str, ...]:
        """Attribute words from the outermost element in."""
        return tuple(w for p in self._line() for w in p.words)


def _attribute_words(attributes: str) -> tuple[str, ...]:
    if "=" not in attributes:
        return ()
    return tuple(w for m in ATTRIBUTE.finditer(attributes) for w in NAME.findall(m[1].lower()))


class Closings:
    """Where the tags of a page close: at the first > outside quotes, or the first of all if a quote stays open.

    All characters that matter are looked at once, from the page's end, so a
    page of tags that never close costs no more than another.
    """

    def __init__(self, page: str):
        self.page = page
        self.at = [m.start() for m in _SPECIAL.finditer(page)]
        self.close = [-1] * (len(self.at) + 1)
        later = {'"': -1, "'": -1}
        self.last = -1
        for k in range(len(self.at) - 1, -1, -1):
            c = page[self.at[k]]
            if c == ">":
                self.close[k] = self.at[k]
                self.last = max(self.last, self.at[k])
            else:
                self.close[k] = self.close[later[c] + 1] if later[c] >= 0 else -1
                later[c] = k

    def after(self, at: int) -> int:
        """The place of the > that closes a tag which is open at ``at``, or -1."""
        found = self.close[bisect_left(self.at, at)]
        return found if found >= 0 else self.plain(at)

    def plain(self, at: int) -> int:
        return self.page.find(">", at) if at <= self.last else -1


class _Stack:
    """Open elements, with the places of each tag and of all blocks among them."""

    def __init__(self) -> None:
        self.items: list[Place] = []
        self.of: dict[str, list[int]] = {}
        self.blocks: list[int] = []

    @property
    def top(self) -> Place | None:
        return self.items[-1] if self.items else None

    def push(self, tag: str, words: tuple[str, ...], link: bool) -> None:
        at = len(self.items)
        self.items.append(Place(tag, words, self.top, link))
        self.of.setdefault(tag, []).append(at)
        if tag in BLOCK:
            self.blocks.append(at)

    def cut(self, at: int) -> None:
        while len(self.items) > at:
            gone = self.items.pop()
            self.of[gone.tag].pop()
            if gone.tag in BLOCK:
                self.blocks.pop()

    def last(self, tag: str) -> int:
        return own[-1] if (own := self.of.get(tag)) else -1

    def end_before(self, tag: str) -> None:
        """Close what the start of ``tag`` ends."""
        ends, walls = ENDS.get(tag, (frozenset(), frozenset()))
        wall = max((self.last(w) for w in walls), default=-1)
        first = [own[k] for e in ends if (own := self.of.get(e)) and (k := bisect_right(own, wall)) < len(own)]
        if first:
            self.cut(min(first))


def blocks(page: str) -> list[Block]:
    """Blocks with text, in page order; the head and raw elements have none. Work is in proportion to the page's length."""
    out: list[Block] = []
    stack, closings = _Stack(), Closings(page)
    parts: list[str] = []
    linked = 0
    cdata = True

    def close_block() -> None:
        nonlocal linked
        if parts:
            joined = "".join(parts)
            text = " ".join((html.unescape(joined) if "&" in joined else joined).split())
            if text and not (stack.top is not None and stack.top.hidden):
                out.append(Block(text, stack.top, min(1.0, linked / max(1, len(joined)))))
            parts.clear()
        linked = 0

    def add(text: str) -> None:
        nonlocal linked
        parts.append(text)
        if stack.top is not None and stack.top.linked:
            linked += len(text)

    at, end = 0, len(page)
    while at < end:
        opened = page.find("<", at)
        if opened != at:
            stop = opened if opened >= 0 else end
            add(page[at:stop])
            at = stop
            continue
        if page.startswith("<!--", at):
            stop = page.find("-->", at + 4)
            at = stop + 3 if stop >= 0 else end
            continue
        if cdata and page.startswith("<![CDATA[", at):
            stop = page.find("]]>", at)
            if cdata := stop >= 0:
                parts.append(page[at + 9 : stop].replace("&", "&amp;"))
                at = stop + 3
                continue
        if page[at + 1 : at + 2] in ("!", "?") and (stop := closings.plain(at)) >= 0:
            at = stop + 1
            continue
        m = OPENING.match(page, at)
        stop = closings.after(m.end()) if m else -1
        if stop < 0:
            add("<")
            at += 1
            continue
        tag, attributes, at = m[2].lower(), page[m.end() : stop], stop + 1
        if m[1]:
            if tag in BLOCK:
                close_block()
            if (i := stack.last(tag)) >= 0:
                crossed = bool(stack.blocks) and stack.blocks[-1] > i
                if crossed:
                    close_block()
                # An inline end tag does not close blocks inside which it stands.
                if tag in BLOCK or not crossed:
                    stack.cut(i)
            continue
        if tag in BLOCK:
            close_block()
            stack.end_before(tag)
        if tag in RAW:
            found = re.compile(rf"</{re.escape(tag)}(?=[\s/>])", re.I).search(page, at)
            stop = closings.plain(found.end()) if found else -1
            at = stop + 1 if stop >= 0 else end
            continue
        if tag == "br":
            parts.append(" ")
        if tag not in VOID and not attributes.endswith("/"):
            stack.push(tag, _attribute_words(attributes), tag == "a" and HREF.search(attributes) is not None)
    close_block()
    return out
