"""Labelled pages to train the block tagger on: made by rule, in many layouts.

A page is a list of sections; every block of text in it is marked as main text or not.
Words are random letters, so that the tagger learns layout and text shape and no words.
"""

from __future__ import annotations

import random

#: Fixed value lists: names that sites give to sections beside the article, and to the article.
BESIDE = {
    "menu": "nav menu navbar navigation breadcrumb toolbar topnav links".split(),
    "header": "header masthead branding logo top site-header banner".split(),
    "footer": "footer site-footer bottom copyright colophon legal".split(),
    "side": "sidebar aside related recommended widget popular trending rail teaser".split(),
    "notice": "cookie notice consent gdpr alert popup modal disclaimer paywall".split(),
    "advert": "ad ads advert advertisement promo sponsored banner-ad adbox sponsor".split(),
    "form": "form search login newsletter subscribe signup contact".split(),
    "comments": "comments comment replies respond discussion reader-comments thread".split(),
    "share": "share social tags meta byline pagination pager".split(),
}
ARTICLE = "content article post entry story main text body article-body post-content entry-content".split()
_TAGS = {
    "menu": ["nav", "nav", "div", "ul"], "header": ["header", "header", "div"], "footer": ["footer", "footer", "div"], "side": ["aside", "aside", "div"],
    "notice": ["div", "section", "aside"], "advert": ["div", "div", "aside", "section"], "form": ["form", "form", "div"], "comments": ["section", "div", "div", "ul"], "share": ["div", "ul", "p"],
}


class Page:
    def __init__(self, seed: int):
        self.r = random.Random(seed)
        self.main: set[str] = set()

    def word(self) -> str:
        return "".join(self.r.choice("aeioulnrstdmcéüß") for _ in range(self.r.randint(2, 9)))

    def text(self, low: int, high: int, marks: bool) -> str:
        w = [self.word() for _ in range(self.r.randint(low, high))]
        w[0] = w[0].capitalize()
        if marks:
            w = [x + self.r.choice([",", ".", ".", "!", "?"]) if self.r.random() < 0.15 else x for x in w]
            w[-1] = w[-1].rstrip(".,!?") + "."
        if self.r.random() < 0.1:
            w = [x + self.r.choice(["***", "!!", "###", " |"]) for x in w]
        return " ".join(w)

    def keep(self, t: str) -> str:
        self.main.add(" ".join(t.split()))
        return t

    def paragraph(self, main: bool) -> str:
        t = self.text(1, 70, self.r.random() < 0.85)
        t = self.keep(t) if main else t
        x = self.r.random()
        if x < 0.15:
            return f"<p><b>{t}<br>"
        if x < 0.22:
            return f"<div>{t}</div>"
        if x < 0.3 and " " in t:
            a, b = t.split(" ", 1)
            return f'<p>{a} <a href="/x">{b}</a></p>' if len(b) < 60 else f"<p><em>{a}</em> {b}</p>"
        if x < 0.34:
            return f"<blockquote><p>{t}</p></blockquote>"
        if x < 0.38:
            return f"<ul><li>{t}</li></ul>"
        return f"<p>{t}</p>"

    def attrs(self, kind: list[str], often: float) -> str:
        if self.r.random() > often:
            return ""
        n = self.r.choice(kind)
        return f' {self.r.choice(["class", "class", "id"])}="{n}"'

    def beside(self, kind: str) -> str:
        tag = self.r.choice(_TAGS[kind])
        plain = tag in ("div", "section", "ul", "p")
        a = self.attrs(BESIDE[kind], 1.0 if plain else 0.5)
        r = self.r
        if kind in ("menu", "share") or kind in ("footer", "side", "header") and r.random() < 0.4:
            items = [self.text(1, 4, False) for _ in range(r.randint(2, 7))]
            inner = "".join(f'<li><a href="/{x}">{x}</a></li>' for x in items)
            inner = inner if tag == "ul" else f"<ul>{inner}</ul>"
        elif kind == "footer":
            inner = f"{r.choice(['&copy; ', '&copy; ', '© ', 'Copyright '])}{self.word()}.example {r.choice(['&middot; ', ''])}{self.text(1, 8, False)}"
        elif kind == "form":
            inner = f'<label>{self.text(1, 4, False)}</label><input name="q"><button>{self.text(1, 2, False)}</button><p>{self.text(2, 14, True)}</p>'
        elif kind == "comments":
            unit = r.choice(["div", "li", "article", "p"])
            inner = f"<h3>{self.text(1, 3, False)}</h3>" + "".join(f'<{unit}{self.attrs(["comment", "reply"], 0.6)}><b>{self.word()}</b><p>{self.text(3, 40, True)}</p></{unit}>' for _ in range(r.randint(1, 4)))
        else:
            inner = "".join(r.choice(["<p>{}</p>", "{}", "<h3>{}</h3>"]).format(self.text(2, 25, r.random() < 0.7)) for _ in range(r.randint(1, 3)))
        return f"<{tag}{a}>{inner}</{tag}>"

    def article(self) -> str:
        r = self.r
        tag = r.choice(["article", "article", "article", "main", "div", "section", "div"])
        a = self.attrs(ARTICLE, 0.95 if tag in ("div", "section") else 0.3)
        title = self.keep(self.text(1, 9, r.random() < 0.4))
        parts = [f"<h1>{title}</h1>"] if r.random() < 0.9 else [f"<header><h1>{title}</h1></header>"]
        for _ in range(r.randint(0, 12)):
            parts.append(self.paragraph(True))
            if r.random() < 0.1:
                parts.append(f"<h2>{self.keep(self.text(1, 7, False))}</h2>")
            if r.random() < 0.06:
                parts.append(self.beside(r.choice(["advert", "side", "share", "form", "notice"])))
        if r.random() < 0.12:
            parts.append(self.beside("comments"))
        return f"<{tag}{a}>{''.join(parts)}</{tag}>"

    def build(self) -> str:
        r = self.r
        before = [k for k in ("header", "menu", "notice", "advert", "form") if r.random() < (0.8 if k == "menu" else 0.35)]
        r.shuffle(before)
        after = [k for k in ("comments", "side", "advert", "share", "form", "notice") if r.random() < 0.3] + ["footer"] * (r.random() < 0.85)
        body = "".join(map(self.beside, before)) + self.article() + "".join(map(self.beside, after))
        if r.random() < 0.2:
            body = f'<div{self.attrs(["wrap", "page", "container", "site"], 0.8)}>{body}</div>'
        return f"<!DOCTYPE html><html><head><title>{self.word()}</title><style>p{{}}</style></head><body>{body}</body></html>"


def labelled_pages(n: int = 700, seed: int = 5) -> list[tuple[str, set[str]]]:
    """``(html, texts of its main blocks)``."""
    out = []
    for k in range(n):
        p = Page(seed * 100_003 + k)
        out.append((p.build(), p.main))
    return out
