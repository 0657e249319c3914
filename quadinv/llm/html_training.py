"""Labelled pages for training the HTML extractor: page layouts drawn at random, each part labelled by what it is.

A part's elements carry data-y="1" (main text) or data-y="0" (everything else); the extractor's parser reads the label of training
pages only and never uses it as a feature. Words are random syllables, so that nothing is learned from the wording; a share of the pages
names nothing, or by hashes, so that the shape of a part has to tell.
"""

from __future__ import annotations

import random

#: Class and id names in common use on the web, by the part of a page that they name.
NAMES = {
    "content": "content article post entry story main-content post-content entry-content article-body post-body body-text story-body page-content text blog-post main page maincontent single hentry prose".split(),
    "menu": "nav menu navbar navigation main-nav top-menu nav-list site-nav breadcrumb breadcrumbs pagination pager menubar toc tabs topnav dropdown".split(),
    "header": "header site-header masthead top-bar logo branding page-header topbar hero-header site-title tagline".split(),
    "footer": "footer site-footer bottom copyright footer-links legal colophon credits page-footer imprint".split(),
    "sidebar": "sidebar side widget widget-area related related-posts recent-posts tag-cloud archive aside rail right-col left-col popular trending more-stories tags categories author-box recommended".split(),
    "notice": "notice cookie cookie-banner cookie-notice consent gdpr alert popup modal overlay disclaimer paywall message warning banner toast privacy".split(),
    "ad": "ad ads advert advertisement banner-ad sponsored sponsor promo promotion adsense ad-slot adbox commercial partner ad-container".split(),
    "form": "form search search-form newsletter subscribe signup login contact-form register subscription search-box".split(),
    "share": "share social social-links share-buttons follow sharing".split(),
    "comments": "comments comment comment-list reply responses discussion disqus respond replies comment-body comment-content user-comment reader-comments feedback".split(),
}
INERT = "wrapper container inner row col clearfix grid box section block layout outer wrap site app root".split()
SYLLABLES = "ba ce di fo gu ha je ki lo mu na pe ri so tu va we xi yo zu an er in on us tion ment ly est".split()


class Page:
    def __init__(self, seed: int):
        self.draw = random.Random(seed)
        self.style = self.draw.choice(("named", "named", "named", "hashed", "plain"))

    def word(self) -> str:
        return "".join(self.draw.choice(SYLLABLES) for _ in range(self.draw.randint(1, 4)))

    def words(self, least: int, most: int) -> str:
        return " ".join(self.word() for _ in range(self.draw.randint(least, most)))

    def sentences(self, least: int, most: int) -> str:
        return " ".join(self.words(4, 18).capitalize() + self.draw.choice("...,!?") for _ in range(self.draw.randint(least, most)))

    def named(self, part: str) -> str:
        """Attributes that name the part, by a hash on pages that do so, and not at all on plain ones."""
        if self.style == "plain":
            return ""
        if self.style == "hashed":
            return f' class="{self.draw.choice(("css", "sc", "x", "jsx", "_"))}-{self.draw.randrange(16**6):06x}"'
        name = self.draw.choice(NAMES[part])
        kind = self.draw.random()
        if kind < 0.45:
            return f' class="{name}"'
        if kind < 0.6:
            return f' class="{self.draw.choice(INERT)} {name}"'
        if kind < 0.85:
            return f' id="{name}"'
        return f' class="{name}" id="{self.draw.choice(NAMES[part])}"'

    def inert(self) -> str:
        return "" if self.draw.random() < 0.5 else f' class="{self.draw.choice(INERT)}"'

    def element(self, tag: str, inner: str, attributes: str = "", y: int | None = None) -> str:
        label = "" if y is None else f' data-y="{y}"'
        return f"<{tag}{attributes}{label}>{inner}</{tag}>"

    def links(self, least: int = 3, most: int = 9, words: tuple[int, int] = (1, 3)) -> str:
        items = [f'<a href="/{self.word()}">{self.words(*words)}</a>' for _ in range(self.draw.randint(least, most))]
        kind = self.draw.random()
        if kind < 0.7:
            return self.element(self.draw.choice(("ul", "ul", "ol")), "".join(f"<li>{i}</li>" for i in items))
        return (" | " if kind < 0.85 else " ").join(items)

    # What isn't main text; each with label 0.

    def menu(self) -> str:
        if self.draw.random() < 0.6:
            return self.element("nav", self.links(), self.draw.choice(("", self.named("menu"), ' role="navigation"')), 0)
        return self.element(self.draw.choice(("div", "ul", "section")), self.links(), self.named("menu"), 0)

    def header(self) -> str:
        inner = f"<a href='/'>{self.words(1, 3)}</a>" + self.draw.choice(("", f"<p>{self.words(3, 8)}</p>", f"<h2>{self.words(1, 4)}</h2>", f"<h1>{self.words(1, 4)}</h1>")) + self.draw.choice(("", self.links()))
        if self.draw.random() < 0.6:
            return self.element("header", inner, self.draw.choice(("", self.named("header"), ' role="banner"')), 0)
        return self.element("div", inner, self.named("header"), 0)

    def footer(self) -> str:
        inner = self.draw.choice((f"&copy; {self.words(2, 5)} &middot; {self.sentences(1, 2)}", f"<p>&copy; {self.words(2, 6)}</p>" + self.links(), f"<p>{self.sentences(1, 3)}</p>", self.links()))
        if self.draw.random() < 0.65:
            return self.element("footer", inner, self.draw.choice(("", self.named("footer"), ' role="contentinfo"')), 0)
        return self.element("div", inner, self.named("footer"), 0)

    def sidebar(self) -> str:
        boxes = "".join(self.element("div", f"<h3>{self.words(1, 3)}</h3>" + self.draw.choice((self.links(3, 8, (2, 6)), f"<p>{self.sentences(1, 4)}</p>")), self.draw.choice(("", self.inert(), self.named("sidebar")))) for _ in range(self.draw.randint(1, 3)))
        if self.draw.random() < 0.6:
            return self.element("aside", boxes, self.draw.choice(("", self.named("sidebar"), ' role="complementary"')), 0)
        return self.element(self.draw.choice(("div", "section")), boxes, self.named("sidebar"), 0)

    def notice(self) -> str:
        inner = self.draw.choice((self.sentences(1, 3), f"<p>{self.sentences(1, 4)}</p>")) + self.draw.choice(("", f"<button>{self.words(1, 2)}</button>", f"<a href='#'>{self.words(1, 2)}</a>"))
        return self.element(self.draw.choice(("div", "div", "section", "aside", "p", "dialog")), inner, self.draw.choice((self.named("notice"), self.named("notice"), ' role="alert"', ' role="dialog"')), 0)

    def ad(self) -> str:
        inner = self.draw.choice((self.sentences(1, 2), f"<p>{self.sentences(1, 3)}</p>", f"<a href='/{self.word()}'>{self.sentences(1, 2)}</a>", f"<h4>{self.words(2, 5)}</h4><p>{self.sentences(1, 2)}</p>"))
        return self.element(self.draw.choice(("div", "div", "aside", "section", "ins", "p")), inner, self.named("ad"), 0)

    def form(self) -> str:
        inner = f"<label>{self.words(1, 4)}</label><input name='q'>" + self.draw.choice(("", f"<p>{self.sentences(1, 2)}</p>")) + f"<button>{self.words(1, 2)}</button>"
        if self.draw.random() < 0.7:
            return self.element("form", inner, self.draw.choice(("", self.named("form"))), 0)
        return self.element("div", self.element("form", inner) if self.draw.random() < 0.5 else f"<p>{self.sentences(1, 2)}</p>" + inner, self.named("form"), 0)

    def share(self) -> str:
        return self.element(self.draw.choice(("div", "ul", "p")), " ".join(f"<a href='#'>{self.word()}</a>" for _ in range(4)), self.named("share"), 0)

    def comments(self) -> str:
        """Rarely on pages that name nothing, for there nothing sets them off from an article."""
        if self.style != "named" and self.draw.random() < 0.85:
            return self.sidebar()
        one = lambda: self.draw.choice((f"<p>{self.sentences(1, 5)}</p>", self.sentences(1, 4), f"<b>{self.word()}</b> <p>{self.sentences(1, 4)}</p>"))
        tag = self.draw.choice(("li", "li", "div", "div", "article"))
        rows = "".join(self.element(tag, one(), self.draw.choice(("", self.named("comments")))) for _ in range(self.draw.randint(1, 6)))
        inner = self.draw.choice(("", f"<h3>{self.words(1, 3)}</h3>")) + (self.element("ol", rows, self.draw.choice(("", self.named("comments")))) if tag == "li" else rows)
        return self.element(self.draw.choice(("section", "div", "div", "aside")), inner, self.named("comments"), 0)

    # Main text; each with label 1.

    def prose(self) -> str:
        """Sentences mostly; now and then a word or two, or many without a stop."""
        kind = self.draw.random()
        if kind < 0.72:
            return self.sentences(1, 8)
        if kind < 0.86:
            return self.words(1, 3).capitalize() + self.draw.choice(".,?. ")
        if kind < 0.95:
            return self.words(3, 120)
        return " ".join(f"{self.word().upper()}!!" for _ in range(self.draw.randint(3, 40)))

    def paragraph(self) -> str:
        text = self.prose()
        kind = self.draw.random()
        if kind < 0.15:
            text = f"<b>{self.words(2, 6)}</b> {text}"
        elif kind < 0.3:
            text = f"{text} <a href='/x'>{self.words(1, 4)}</a> {self.sentences(1, 3)}"
        elif kind < 0.36:
            return f'<p data-y="1"><b>{text}<br>'  # tags left open
        elif kind < 0.4:
            return f'<p data-y="1">{text}'
        return self.element("p", text, self.inert() if kind > 0.95 else "", 1)

    def passage(self) -> str:
        kind = self.draw.random()
        if kind < 0.72:
            return self.paragraph()
        if kind < 0.8:
            return self.element(self.draw.choice(("h2", "h3", "h4")), self.words(2, 8), "", 1)
        if kind < 0.86:
            return self.element(self.draw.choice(("ul", "ol")), "".join(self.element("li", self.draw.choice((self.words(3, 12), self.sentences(1, 2))), "", 1) for _ in range(self.draw.randint(2, 6))), "", 1)
        if kind < 0.9:
            return self.element("blockquote", self.draw.choice((self.sentences(1, 3), self.paragraph())), "", 1)
        if kind < 0.93:
            rows = "".join("<tr data-y='1'>" + "".join(self.element("td", self.words(1, 4), "", 1) for _ in range(3)) + "</tr>" for _ in range(self.draw.randint(2, 4)))
            return self.element("table", rows, "", 1)
        if kind < 0.95:
            return self.element("pre", self.words(5, 20), "", 1)
        if kind < 0.97:
            return self.element("figure", '<img src="x.png">' + self.element("figcaption", self.words(3, 10), "", 1), "", 1)
        return self.element("div", self.sentences(1, 6), "", 1)

    def article(self) -> str:
        parts = [self.element(self.draw.choice(("h1", "h1", "h2")), self.draw.choice((self.words(2, 10), self.words(2, 10), self.sentences(1, 3))), "", 1)] if self.draw.random() < 0.85 else []
        for _ in range(self.draw.choice((1, 1, 2, self.draw.randint(1, 14), self.draw.randint(3, 14), self.draw.randint(5, 25)))):
            parts.append(self.passage())
            if self.draw.random() < 0.06:
                parts.append(self.draw.choice((self.ad, self.share, self.form, self.notice))())
        if self.draw.random() < 0.15:
            parts.append(self.draw.choice((self.share, self.comments, self.sidebar))())
        if self.draw.random() < 0.25:
            head = self.element("h1", self.words(2, 10), "", 1) + self.draw.choice(("", "", self.element("p", self.sentences(1, 2), "", 1)))
            name = self.draw.choice(("", "", ' class="entry-header"', ' class="post-header"', ' class="article-header"')) if self.style == "named" else self.named("header")
            parts.insert(0, self.element(self.draw.choice(("header", "header", "div")), head, name, 1))
        if self.draw.random() < 0.2:
            parts.append(self.element("footer", self.draw.choice((self.links(1, 5), f"{self.words(1, 3)} <a href='/t'>{self.words(1, 2)}</a>")), self.draw.choice(("", self.named("footer"))), 0))
        if self.draw.random() < 0.15:
            parts.insert(self.draw.randint(1, len(parts)), self.element("aside", f"<h3>{self.words(1, 3)}</h3>" + self.links(2, 5, (2, 6)), self.draw.choice(("", self.named("sidebar"))), 0))
        inner = "".join(parts)
        kind = self.draw.random()
        if self.style != "named" and kind < 0.4:
            return self.element("div", inner, self.named("content"), 1)
        if kind < 0.45:
            return self.element("article", inner, self.draw.choice(("", self.named("content"))), 1)
        if kind < 0.6:
            return self.element("main", inner, self.draw.choice(("", self.named("content"), ' role="main"')), 1)
        if kind < 0.95:
            return self.element(self.draw.choice(("div", "section")), inner, self.named("content"), 1)
        return self.element("div", inner, self.inert(), 1)

    def rights(self) -> str:
        """A copyright line in an element that says nothing."""
        return self.element(self.draw.choice(("div", "p", "center", "div")), self.draw.choice((f"&copy; {self.draw.randrange(1995, 2030)} {self.words(1, 4)}", f"&copy; {self.words(2, 5)}. {self.sentences(1, 1)}", f"{self.words(1, 2)} &copy; {self.words(1, 3)} | <a href='/p'>{self.words(1, 2)}</a> | <a href='/c'>{self.words(1, 2)}</a>")), "", 0)

    def table_page(self) -> str:
        """Menu, article and margin as cells of one table."""
        menu = self.draw.choice((self.links(), "<br>".join(f"<a href='/{self.word()}'>{self.words(1, 2)}</a>" for _ in range(self.draw.randint(3, 8)))))
        main = "".join([self.element("h1", self.words(2, 8), "", 1)] + [self.passage() for _ in range(self.draw.randint(2, 8))])
        if self.draw.random() < 0.3:
            main = f"<b>{self.words(2, 6)}</b><br><br>" + "<br><br>".join(self.sentences(2, 6) for _ in range(self.draw.randint(2, 6)))
        cells = [self.element("td", menu, ' width="150"', 0), self.element("td", main, "", 1)] + ([self.element("td", self.links(2, 6), "", 0)] if self.draw.random() < 0.4 else [])
        top = f"<tr data-y='0'><td colspan=3 data-y=\"0\"><a href='/'>{self.words(1, 3)}</a></td></tr>" if self.draw.random() < 0.5 else ""
        foot = f"<tr><td colspan=3 data-y=\"0\">&copy; {self.words(1, 4)}</td></tr>" if self.draw.random() < 0.5 else ""
        return f"<table>{top}<tr>{''.join(cells)}</tr>{foot}</table>"

    def html(self) -> str:
        if self.draw.random() < 0.06:
            return f"<html><body>{self.table_page()}{self.draw.choice(('', self.rights(), self.footer()))}</body></html>"
        before = [f() for f in (self.notice, self.header, self.menu, self.ad, self.form) if self.draw.random() < 0.5]
        after = [f() for f in (self.share, self.comments, self.sidebar, self.ad, self.form, self.notice, self.menu) if self.draw.random() < 0.35]
        if self.draw.random() < 0.7:
            after.append(self.footer())
        elif self.draw.random() < 0.7:
            after.append(self.rights())
        self.draw.shuffle(before)
        middle = self.article()
        if self.draw.random() < 0.3:
            middle = self.element(self.draw.choice(("div", "main", "section")), middle + self.draw.choice(("", self.sidebar(), self.comments())), self.inert())
        inner = "".join(before) + middle + "".join(after)
        if self.draw.random() < 0.3:
            inner = self.element("div", inner, self.inert())
        head = f"<head><meta charset='utf-8'><title>{self.words(2, 8)}</title><style>p{{margin:0}}</style></head>"
        return f"<!DOCTYPE html><html>{head}<body{self.inert()}>{inner}</body></html>"


def labelled_pages(n: int, seed: int = 0) -> list[str]:
    return [Page(seed * 1_000_003 + k).html() for k in range(n)]
