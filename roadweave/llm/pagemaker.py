"""Labelled pages to train the block labeller on: many layouts, each block known to be main text or not."""

from __future__ import annotations

import html
from random import Random

SYLLABLES = "an en er th in on re at ti es or he nd st ou ea le la de ai que eu ent ch ung sch ber ein aus ver ge el os as ar io ón mi ra ta co ño ka lo vi no pa tu su ri".split()
#: Words that boilerplate of each kind tends to have, beside any others.
HINTS = {
    "nav": "home about contact news blog archive login menu search start",
    "header": "welcome site the daily official portal",
    "footer": "copyright © 2020 all rights reserved privacy terms imprint ·",
    "sidebar": "related popular recent posts tags categories more read",
    "notice": "cookie cookies we use accept consent subscribe newsletter",
    "ad": "ad sponsored buy now offer save click here",
    "form": "name email submit send search your message",
    "comments": "reply says comment posted by ago likes",
}
NAMES = {
    "nav": "nav navbar menu topnav breadcrumb breadcrumbs main-menu navigation pagination",
    "header": "header site-header masthead banner top branding",
    "footer": "footer site-footer bottom copyright colophon credits",
    "sidebar": "sidebar side widget related aside recommended popular more-links tags share social",
    "notice": "cookie notice cookie-banner consent alert popup modal newsletter subscribe",
    "ad": "ad ads advert advertisement banner-ad sponsored promo promotion",
    "form": "search form contact-form login signup",
    "comments": "comments comment-list commentlist replies discussion responses",
    "main": "content article post entry main story entry-content post-body article-body text body",
}
NEUTRAL = "box row col wrap inner block item c1 x container module".split()


class PageMaker:
    """Writes random pages with the same layout rules and remembers each block's label."""

    def __init__(self, seed: int):
        self.r = Random(seed)

    def word(self) -> str:
        return "".join(self.r.choice(SYLLABLES) for _ in range(self.r.choice((1, 1, 2, 2, 3))))

    def sentence(self, low: int, high: int, kind: str | None = None) -> str:
        words = [self.word() for _ in range(self.r.randint(low, high))]
        if kind and self.r.random() < 0.5:
            for hint in self.r.sample(HINTS[kind].split(), 2):
                words.insert(self.r.randrange(len(words) + 1), hint)
        # Text of any kind may be shouted, set in bars, or full of signs and numbers.
        odd = self.r.random()
        if odd < 0.04:
            words = [w.upper() + self.r.choice(("!!", "")) for w in words]
        elif odd < 0.08:
            words = [x for w in words for x in (w, self.r.choice(("|", "-", "·", w)))]
        elif odd < 0.12:
            words = [w + self.r.choice(("%%%", "***", "$$$", "&&&", "###", "")) for w in words]
        elif odd < 0.16:
            words.insert(self.r.randrange(len(words) + 1), str(self.r.randrange(10 ** self.r.randint(1, 16))))
        text = " ".join(words)
        return (text if odd < 0.04 else text.capitalize()) + self.r.choice((".", ".", "", "!", "?"))

    def named(self, kind: str, tag: str) -> str:
        """An opening tag, mostly with a telling class or id."""
        if self.r.random() < 0.75:
            name = self.r.choice(NAMES[kind].split())
        else:
            name = self.r.choice(NEUTRAL)
        how = self.r.choice(("class", "class", "id"))
        return f'<{tag} {how}="{name}">' if self.r.random() < 0.85 else f"<{tag}>"

    def put(self, text: str, label: int) -> str:
        self.labels.append((" ".join(text.split()), label))
        return html.escape(text, quote=False)

    def links(self, n: int, kind: str, tag: str = "li") -> str:
        inner = "".join(f'<{tag}><a href="/{self.word()}">{self.put(self.sentence(1, 4, kind), 0)}</a></{tag}>' for _ in range(n))
        return f"<ul>{inner}</ul>" if tag == "li" else inner

    def boiler(self, kind: str) -> str:
        tag = {"nav": ("nav", "div"), "header": ("header", "div"), "footer": ("footer", "div"), "sidebar": ("aside", "div", "section"), "notice": ("div", "p", "section"), "ad": ("div", "aside", "div"), "form": ("form", "div"), "comments": ("div", "section", "ol")}[kind]
        tag = self.r.choice(tag)
        opening = self.named(kind, tag) if kind in ("ad", "notice", "comments") or tag in ("div", "section") or self.r.random() < 0.5 else f"<{tag}>"
        r = self.r.random()
        if kind == "nav":
            inner = self.links(self.r.randint(2, 7), kind, self.r.choice(("li", "li", "span" if r < 0 else "p")))
        elif kind == "comments":
            each = lambda: f'<div class="{self.r.choice(("comment", "reply", "c1"))}"><p>{self.put(self.sentence(1, 3, kind), 0)}</p>' + "".join(f"<p>{self.put(self.sentence(4, 40, kind), 0)}</p>" for _ in range(self.r.randint(1, 2))) + "</div>"
            inner = "".join(f"<li>{each()}</li>" if tag == "ol" else each() for _ in range(self.r.randint(1, 4)))
            if tag != "ol" and self.r.random() < 0.6:
                inner = f"<h3>{self.put(self.sentence(1, 3, kind), 0)}</h3>" + inner
        elif kind == "form":
            inner = f"<label>{self.put(self.sentence(1, 4, kind), 0)}</label><input><button>{self.put(self.sentence(1, 2, kind), 0)}</button>"
            if tag == "div":
                inner = f"<form>{inner}</form>"
        elif kind == "sidebar" and r < 0.6:
            inner = f"<h3>{self.put(self.sentence(1, 4, kind), 0)}</h3>" + self.links(self.r.randint(2, 6), kind)
        elif kind in ("ad", "notice", "footer", "header") and r < 0.6:
            inner = self.put(self.sentence(3, 25, kind), 0)
        else:
            inner = "".join(f"<p>{self.put(self.sentence(3, 25, kind), 0)}</p>" for _ in range(self.r.randint(1, 2)))
            if kind == "footer" and self.r.random() < 0.5:
                inner += self.links(self.r.randint(2, 5), kind)
        return f"{opening}{inner}</{tag}>"

    def main(self) -> str:
        tag = self.r.choice(("article", "article", "main", "div", "div", "section"))
        opening = f"<{tag}>" if tag in ("article", "main") and self.r.random() < 0.6 else self.named("main", tag)
        out = [f"<h1>{self.put(self.sentence(2, 10), 1)}</h1>"] if self.r.random() < 0.9 else []
        for _ in range(self.r.choice((0, 1, 2, 3, 5, 8, 12, 25))):
            kind = self.r.random()
            if kind < 0.7:
                text = self.put(self.sentence(*self.r.choice(((1, 2), (1, 6), (5, 30), (20, 90)))), 1)
                style = self.r.random()
                out.append(f"<p>{text}</p>" if style < 0.75 else f"<p><b>{text}<br>" if style < 0.85 else f"<p>{text}" if style < 0.93 else f"<div>{text}</div>")
            elif kind < 0.78:
                out.append(f"<h2>{self.put(self.sentence(1, 7), 1)}</h2>")
            elif kind < 0.86:
                out.append("<ul>" + "".join(f"<li>{self.put(self.sentence(2, 15), 1)}</li>" for _ in range(self.r.randint(2, 4))) + "</ul>")
            elif kind < 0.91:
                out.append(f"<blockquote>{self.put(self.sentence(5, 30), 1)}</blockquote>")
            elif kind < 0.95:
                out.append("<table>" + "".join("<tr>" + "".join(f"<td>{self.put(self.sentence(1, 4), 1)}</td>" for _ in range(2)) + "</tr>" for _ in range(2)) + "</table>")
            else:
                out.append(self.boiler(self.r.choice(("ad", "sidebar", "form"))))
        return f"{opening}{''.join(out)}</{tag}>"

    def page(self) -> tuple[str, list[tuple[str, int]]]:
        """A page and its blocks' texts with their labels."""
        self.labels: list[tuple[str, int]] = []
        r = self.r
        before = [k for k, p in (("notice", 0.3), ("header", 0.5), ("nav", 0.8), ("ad", 0.5), ("form", 0.25), ("sidebar", 0.2)) if r.random() < p]
        after = [k for k, p in (("sidebar", 0.45), ("ad", 0.3), ("comments", 0.45), ("form", 0.2), ("nav", 0.15), ("footer", 0.85), ("notice", 0.15)) if r.random() < p]
        body = "".join(self.boiler(k) for k in before)
        wrap = r.random() < 0.3
        body += (f'<div class="{r.choice(NEUTRAL)}">' if wrap else "") + self.main() + ("</div>" if wrap else "")
        body += "".join(self.boiler(k) for k in after)
        return f"<html><head><title>{self.word()}</title></head><body>{body}</body></html>", self.labels
