"""Labelled pages to train on: each is generated with its article blocks known.

Layouts, element and class names, languages' word shapes and the amount of everything vary at random, so
the extractor learns from tags, names and text shapes together and not from one site's template.
"""

from __future__ import annotations

import random
from html import escape

# Names that sites give to parts of a page.
CONTENT = "content main article post entry story body text article-body post-content entry-content story-body main-content page-content rich-text".split()
MENUS = "menu nav navbar navigation main-nav breadcrumb breadcrumbs topbar tabs pagination pager toc-links links".split()
HEADERS = "header masthead site-header top branding logo banner-top page-header".split()
FOOTERS = "footer site-footer bottom copyright legal colophon footer-links".split()
SIDES = "sidebar side aside related recommended widget rail popular trending most-read more-stories teaser".split()
ADVERTS = "ad ads advert advertisement banner sponsor sponsored promo ad-slot adsbox commercial".split()
NOTICES = "cookie cookie-notice consent notice alert gdpr popup modal overlay disclaimer paywall message warning announcement".split()
FORMS = "form search newsletter subscribe login signup contact-form subscription".split()
COMMENTS = "comments comment comment-list reply replies responses discussion disqus reader-comments user-comments".split()
SHARES = "share social sharing tools print follow buttons".split()
NEUTRAL = "wrapper container row col inner section block box grid outer page layout item c1 x7 left right clearfix".split()
COPY = ["© 2024 {}", "&copy; {} · All rights reserved", "Copyright {} &middot; Terms", "{} · Impressum", "&copy; {} {}"]
CUES = {
    "notice": ["We use cookies {}", "This site uses cookies {}.", "Accept all {}", "Please note: {}"],
    "form": ["Email {}", "Search", "Subscribe to {}", "Sign up", "Password", "Your name"],
    "advert": ["Advertisement {}", "Sponsored: {}.", "Buy now {}", "{}."],
    "side": ["Related", "Most read", "More from {}", "You may also like"],
    "comment": ["{} says:", "Reply", "{} comments", "Posted by {}"],
}


class PageMaker:
    """Pages from one seed. page() returns (html, blocks' labels in page order, their texts)."""

    def __init__(self, seed: int):
        self.r = random.Random(seed)
        self.syllables = ["".join(self.r.choice("bcdfghlmnprstvéäöñ" if i % 2 == 0 else "aeiouèü") for i in range(self.r.choice((2, 2, 3)))) for _ in range(60)]

    def word(self) -> str:
        return "".join(self.r.choice(self.syllables) for _ in range(self.r.choice((1, 1, 2, 2, 3))))

    def words(self, low: int, high: int) -> str:
        return " ".join(self.word() for _ in range(self.r.randint(low, high)))

    def sentences(self, low: int, high: int) -> str:
        marks = self.r.choice(("", "", "", "", "", "!!", "***"))
        return " ".join((self.words(2, 18).capitalize() + self.r.choice(".....!?")).replace(" ", f"{marks} ") for _ in range(self.r.randint(low, high)))

    def named(self, names: list[str], tag: str, inner: str) -> str:
        """A tag around inner, its class or id from names, mixed with neutral words."""
        r = self.r
        name = r.choice(names)
        if r.random() < 0.3:
            name = f"{r.choice(NEUTRAL)} {name}" if r.random() < 0.5 else f"{name} {r.choice(NEUTRAL)}"
        if r.random() < 0.2:
            name = f"{name}-{r.choice(NEUTRAL)}"
        return f'<{tag} {r.choice(("class", "class", "id"))}="{name}">{inner}</{tag}>'

    def keep(self, text: str, label: int, tag: str, decorate: bool = False) -> str:
        """A leaf block with its label noted."""
        self.labels.append((" ".join(text.split()), label))
        body = escape(text, quote=False)
        if decorate and self.r.random() < 0.35 and " " in text:
            first, rest = body.split(" ", 1)
            tag_in = self.r.choice(("b", "em", "i", "strong", "span", "a href='/x'"))
            body = f"<{tag_in}>{first}</{tag_in.split()[0]}> {rest}"
        if decorate and self.r.random() < 0.1:
            body += "<br>"
        open_only = tag == "p" and self.r.random() < 0.15
        return f"<{tag}>{body}" + ("" if open_only else f"</{tag}>")

    def link(self, text: str, tag: str) -> str:
        self.labels.append((text, 0))
        return f'<{tag}><a href="/{self.word()}">{escape(text, quote=False)}</a></{tag}>'

    def links(self, low: int, high: int, words=(1, 4)) -> str:
        items = "".join(self.link(self.words(*words), "li") for _ in range(self.r.randint(low, high)))
        return f"<ul>{items}</ul>"

    def cue(self, kind: str, tag: str) -> str:
        text = self.r.choice(CUES[kind]).replace("{}", self.words(1, 12))
        return self.keep(text, 0, tag)

    def article(self) -> str:
        r, parts = self.r, []
        if r.random() < 0.85:
            parts.append(self.keep(self.words(2, 12).capitalize() + r.choice(("", ".", "?")), 1, "h1"))
        for _ in range(r.choice((1, 2, 3, 5, 8, 14, 20))):
            kind = r.random()
            if kind < 0.68:
                parts.append(self.keep(self.sentences(1, r.choice((1, 2, 6, 12))), 1, "p", True))
            elif kind < 0.78:
                parts.append(self.keep(self.words(1, 7).capitalize(), 1, r.choice(("h2", "h3"))))
            elif kind < 0.85:
                tag = r.choice(("ul", "ol"))
                parts.append(f"<{tag}>" + "".join(self.keep(self.sentences(1, 1) if r.random() < 0.6 else self.words(1, 8), 1, "li", True) for _ in range(r.randint(2, 6))) + f"</{tag}>")
            elif kind < 0.89:
                inner = self.keep(self.sentences(1, 3), 1, r.choice(("p", "div")))
                parts.append(f"<blockquote>{inner}</blockquote>")
            elif kind < 0.92:
                rows = "".join("<tr>" + "".join(self.keep(self.words(1, 4), 1, "td") for _ in range(3)) + "</tr>" for _ in range(r.randint(1, 4)))
                parts.append(f"<table>{rows}</table>")
            elif kind < 0.94:
                parts.append(f"<figure><img src='a.png'>{self.keep(self.words(3, 12), 1, 'figcaption')}</figure>")
            elif kind < 0.95:
                parts.append(self.keep(self.words(2, 30), 1, "pre"))
            elif kind < 0.97:
                parts.append(self.named(ADVERTS, "div", self.cue("advert", r.choice(("p", "span", "div"))) if r.random() < 0.5 else self.keep(self.sentences(1, 2), 0, "p")))
            elif kind < 0.985:
                parts.append(self.named(SIDES, r.choice(("aside", "div")), self.cue("side", "h3") + self.links(1, 4, (3, 9))))
            else:
                parts.append(self.named(SHARES, "div", self.links(2, 4, (1, 1))))
        return "".join(parts)

    def boilerplate(self, kind: str) -> str:
        r = self.r
        if kind == "menu":
            tag = r.choice(("nav", "nav", "div", "ul"))
            inner = self.links(3, 9, (1, 3)) if tag != "ul" else "".join(self.link(self.words(1, 3), "li") for _ in range(r.randint(3, 9)))
            return f"<nav>{inner}</nav>" if tag == "nav" and r.random() < 0.5 else self.named(MENUS, tag, inner)
        if kind == "header":
            inner = self.keep(self.words(1, 4).title(), 0, r.choice(("div", "p", "h2", "h1"))) + (self.keep(self.words(3, 9), 0, "p") if r.random() < 0.5 else "") + (self.links(2, 5) if r.random() < 0.4 else "")
            return f"<header>{inner}</header>" if r.random() < 0.5 else self.named(HEADERS, r.choice(("div", "header")), inner)
        if kind == "footer":
            inner = (self.links(2, 6) if r.random() < 0.5 else "") + (self.keep(self.sentences(1, 2), 0, "p") if r.random() < 0.5 else "")
            line = r.choice(COPY).replace("{}", self.words(1, 8)) + r.choice(("", ".", " " + self.sentences(1, 2)))
            bare = r.random() < 0.4
            if bare and not inner:
                self.labels.append((line, 0))
                inner = line
            else:
                self.labels.append((line, 0))
                inner += f"<p>{line}</p>"
            return f"<footer>{inner}</footer>" if r.random() < 0.5 else self.named(FOOTERS, r.choice(("div", "footer")), inner)
        if kind == "side":
            inner = self.cue("side", r.choice(("h3", "h4", "div"))) + (self.links(2, 8, (3, 10)) if r.random() < 0.7 else "") + (self.keep(self.sentences(1, 3), 0, "p") if r.random() < 0.6 else "")
            return f"<aside>{inner}</aside>" if r.random() < 0.4 else self.named(SIDES, r.choice(("aside", "div", "section")), inner)
        if kind == "advert":
            bare = self.sentences(1, 3)
            if r.random() < 0.5:
                self.labels.append((" ".join(bare.split()), 0))
                return self.named(ADVERTS, r.choice(("div", "section", "aside")), bare)
            return self.named(ADVERTS, r.choice(("div", "section", "aside")), self.keep(bare, 0, "p") if r.random() < 0.5 else self.cue("advert", "p"))
        if kind == "notice":
            inner = (self.cue("notice", "p") if r.random() < 0.5 else self.keep(self.sentences(1, 3), 0, r.choice(("p", "div")))) + (self.keep(self.words(1, 2), 0, "button") if r.random() < 0.6 else "")
            return self.named(NOTICES, r.choice(("div", "section", "dialog", "aside")), inner)
        if kind == "form":
            extra = self.keep(self.sentences(1, 2), 0, "p") if r.random() < 0.5 else ""
            fields = "".join(self.cue("form", r.choice(("label", "p", "div", "legend", "button", "h3"))).replace("<label>", "<div><label>").replace("</label>", "</label></div>") + "<input name='q'>" for _ in range(r.randint(1, 4)))
            return f"<form action='/s'>{extra}{fields}</form>" if r.random() < 0.6 else self.named(FORMS, "div", f"<form>{extra}{fields}</form>")
        if kind == "share":
            return self.named(SHARES, "div", self.links(2, 5, (1, 2)))
        each = ""
        for _ in range(r.randint(1, 6)):
            one = (self.cue("comment", r.choice(("div", "h4", "p"))) if r.random() < 0.8 else "") + "".join(self.keep(self.sentences(1, 5), 0, "p") for _ in range(r.randint(1, 2)))
            tag = r.choice(("div", "li", "article"))
            each += self.named(COMMENTS, tag, one) if r.random() < 0.7 else f"<{tag}>{one}</{tag}>"
        return self.named(COMMENTS, r.choice(("div", "section", "ol", "aside")), each)

    def wrap(self, inner: str) -> str:
        for _ in range(self.r.choice((0, 0, 1, 2))):
            inner = self.named(NEUTRAL, "div", inner)
        return inner

    def page(self) -> tuple[str, list[tuple[str, int]]]:
        r = self.r
        self.labels: list[tuple[str, int]] = []
        before = [k for k in ("notice", "header", "menu", "form", "advert", "side") if r.random() < 0.45]
        after = [k for k in ("share", "form", "comment", "side", "advert", "menu", "notice") if r.random() < 0.4] + ["footer"] * (r.random() < 0.85)
        r.shuffle(before)
        html = "".join(self.wrap(self.boilerplate(k)) for k in before)
        style = r.random()
        if style < 0.35:
            body = f"<article>{self.article()}</article>"
        elif style < 0.5:
            body = f"<main>{self.article()}</main>"
        elif style < 0.6:
            body = f"<main>{self.named(CONTENT, 'article', self.article())}</main>"
        elif style < 0.9:
            body = self.named(CONTENT, r.choice(("div", "section")), self.article())
        else:
            body = self.named(NEUTRAL, "div", self.article())
        if r.random() < 0.1:  # comments under the text, inside its container
            body = body[: body.rindex("</")] + self.boilerplate("comment") + body[body.rindex("</") :]
        html += self.wrap(body) + "".join(self.wrap(self.boilerplate(k)) for k in after)
        head = f"<head><meta charset='utf-8'><title>{self.words(2, 6)}</title><script>var a = '<p>no</p>';</script><style>p {{}}</style></head>"
        return f"<!DOCTYPE html><html>{head}<body>{html}<!-- end --></body></html>", self.labels
