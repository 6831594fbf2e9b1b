"""Labelled pages to train the content model on: varied layouts of invented words, every element marked content or not."""

from __future__ import annotations

import random

MARK = "data-y"
_PARTS = "ka lo mi ren tus var el on shi ter par dun que sa vo lim nor est i a".split()


class Maker:
    def __init__(self, seed: int):
        self.r = random.Random(seed)

    def words(self, low: int, high: int) -> str:
        n = self.r.randint(low, high)
        return " ".join("".join(self.r.choices(_PARTS, k=self.r.randint(1, 4))) for _ in range(n))

    def sentence(self, low: int = 4, high: int = 18) -> str:
        text = self.words(low, high)
        if self.r.random() < 0.3:
            text = text.replace(" ", ", ", 1)
        return text.capitalize() + self.r.choice(".....!?") + (self.r.choice(["***", "", "###"]) if self.r.random() < 0.05 else "")

    def el(self, tag: str, inner: str, y: int, **attrs: str) -> str:
        more = "".join(f' {k.strip("_")}="{v}"' for k, v in attrs.items() if v)
        return f'<{tag} {MARK}="{y}"{more}>{inner}</{tag}>'

    def link(self, low: int = 1, high: int = 3) -> str:
        return f'<a href="/x">{self.words(low, high)}</a>'

    def links(self, y: int = 0) -> str:
        items = [self.link() for _ in range(self.r.randint(2, 9))]
        if self.r.random() < 0.7:
            return self.el("ul", "".join(self.el("li", i, y) for i in items), y)
        return self.r.choice([" | ", " ", " &middot; "]).join(items)

    def paragraph(self) -> str:
        text = " ".join(self.sentence() for _ in range(self.r.choice([1, 1, 2, 3, 5])))
        if self.r.random() < 0.12:
            text = self.words(1, 2).capitalize() + "."
        if self.r.random() < 0.25:
            text += " " + self.link() + " " + self.sentence()
        return text

    def body_block(self) -> str:
        k = self.r.random()
        if k < 0.62:
            return self.el("p", self.paragraph(), 1)
        if k < 0.74:
            return self.el(self.r.choice(["h2", "h3", "h2", "h4"]), self.words(1, 6).capitalize(), 1)
        if k < 0.82:
            return self.el(self.r.choice(["ul", "ol"]), "".join(self.el("li", self.words(2, 14), 1) for _ in range(self.r.randint(2, 5))), 1)
        if k < 0.87:
            return self.el("blockquote", self.el("p", self.paragraph(), 1), 1)
        if k < 0.90:
            return self.el("table", "".join(self.el("tr", "".join(self.el("td", self.words(1, 3), 1) for _ in range(3)), 1) for _ in range(3)), 1)
        if k < 0.93:
            return self.el("pre", self.words(4, 20), 1)
        if k < 0.96:
            return self.el("div", self.paragraph(), 1)
        return self.el("figure", "<img src=x>" + self.el("figcaption", self.sentence(), 1), 1)

    def advert(self) -> str:
        name = self.r.choice(["ad", "ads", "advert", "advertisement", "ad-slot", "sponsored", "promo", "banner", "ad-box", "adsense"])
        return self.el(self.r.choice(["div", "div", "aside", "section", "p"]), self.r.choice([self.sentence(2, 14), self.el("p", self.sentence(3, 16), 0), self.words(2, 7), self.sentence() + " " + self.link()]), 0, **self.named(name))

    def named(self, name: str) -> dict[str, str]:
        name = name + self.r.choice(["", "", "-1", " box", "_x"])
        return {self.r.choice(["class_", "class_", "id"]): name}

    def comments(self) -> str:
        one = lambda: self.el(self.r.choice(["div", "li", "article"]), self.r.choice(["", self.el("div", self.words(1, 2), 0, class_="author")]) + self.r.choice([self.el("p", self.paragraph(), 0), self.sentence()]), 0, class_=self.r.choice(["comment", "comment-body", "reply", ""]))
        head = self.el(self.r.choice(["h2", "h3", "h4"]), self.words(1, 2), 0) if self.r.random() < 0.7 else ""
        return self.el(self.r.choice(["section", "div", "ol", "div"]), head + "".join(one() for _ in range(self.r.randint(1, 5))), 0, **self.named(self.r.choice(["comments", "comment-list", "comment-section", "disqus", "responses", "discussion"])))

    def furniture(self) -> str:
        """A piece that is no content, to stand outside the article."""
        r = self.r
        k = r.randrange(11)
        if k == 0:
            return self.el("nav", self.links(), 0, class_=r.choice(["", "menu", "navbar"]))
        if k == 1:
            return self.el("div", self.links(), 0, **self.named(r.choice(["menu", "nav", "navigation", "breadcrumb", "breadcrumbs", "topnav"])))
        if k == 2:
            return self.el(r.choice(["header", "div"]), self.el(r.choice(["div", "h1", "p", "a"]), self.words(1, 4), 0) + r.choice(["", self.links(), self.el("p", self.sentence(2, 8), 0)]), 0, **self.named(r.choice(["header", "site-header", "masthead", "logo"])))
        if k == 3:
            return self.el(r.choice(["aside", "aside", "div"]), r.choice([self.el("h3", self.words(1, 3), 0), ""]) + r.choice([self.links(), self.el("p", self.paragraph(), 0), self.sentence()]), 0, **self.named(r.choice(["sidebar", "widget", "related", "side", "recommended"])))
        if k == 4:
            return self.advert()
        if k == 5:
            return self.el(r.choice(["form", "div"]), self.el("label", self.words(1, 3), 0) + "<input name=q>" + self.el("button", self.words(1, 2), 0) + r.choice(["", self.el("p", self.sentence(3, 10), 0)]), 0, **self.named(r.choice(["search", "form", "newsletter", "signup", "subscribe", "login"])))
        if k == 6:
            return self.el(r.choice(["div", "section", "aside"]), r.choice([self.el("p", self.sentence(5, 25), 0), self.sentence(4, 25)]) + r.choice(["", self.el("button", self.words(1, 2), 0)]), 0, **self.named(r.choice(["cookie", "cookie-notice", "notice", "consent", "gdpr", "alert", "popup", "cookie-banner"])))
        if k == 7:
            return self.el("div", self.links() if r.random() < 0.5 else " ".join(self.link(1, 1) for _ in range(4)), 0, **self.named(r.choice(["share", "social", "share-links", "tags"])))
        if k == 8:
            return self.comments()
        if k == 9:
            return self.el("aside", r.choice([self.el("p", self.paragraph(), 0), self.sentence(3, 20)]), 0)
        return self.el("form", self.el("p", self.sentence(2, 9), 0) + "<input><input>" + self.el("button", self.words(1, 2), 0), 0)

    def footer(self) -> str:
        r = self.r
        return self.el(r.choice(["footer", "footer", "div"]), r.choice(["&copy; " + self.words(1, 4), self.el("p", "&copy; 2024 " + self.words(1, 6), 0), self.links() + self.el("p", self.sentence(3, 14), 0), self.words(2, 8)]), 0, **(self.named(r.choice(["footer", "site-footer", "copyright", "bottom"]))))

    def page(self) -> str:
        r = self.r
        inner = [self.body_block() for _ in range(r.choice([1, 2, 3, 5, 8, 14, 25]))]
        if r.random() < 0.8:
            inner.insert(0, self.el("h1", self.words(1, 9).capitalize(), 1))
        if r.random() < 0.25:
            inner.insert(r.randint(1, len(inner)), self.advert())
        if r.random() < 0.12:
            inner.append(self.comments())
        if r.random() < 0.1:
            inner.append(self.furniture())
        text = "".join(inner)
        k = r.random()
        if k < 0.5:
            main = self.el("article", text, 1, **(self.named(r.choice(["post", "article", "entry", "story"])) if r.random() < 0.4 else {}))
        elif k < 0.65:
            main = self.el("main", text, 1)
        elif k < 0.9:
            main = self.el(r.choice(["div", "div", "section", "td"]), text, 1, **self.named(r.choice(["content", "post-content", "entry", "article-body", "main", "story", "text", "body", "page"])))
        elif k < 0.96:
            main = self.el("div", text, 1)
        else:
            main = text
        if r.random() < 0.3:
            main = self.el(r.choice(["main", "div", "section"]), main + (self.furniture() if r.random() < 0.3 else ""), 1, **(self.named(r.choice(["container", "wrapper", "main", "content"])) if r.random() < 0.6 else {}))
        before = "".join(self.furniture() for _ in range(r.choice([0, 1, 2, 2, 3])))
        after = "".join(self.furniture() for _ in range(r.choice([0, 0, 1, 2, 3])))
        body = before + main + after + (self.footer() if r.random() < 0.85 else "")
        return f'<!DOCTYPE html><html {MARK}="1"><head><title>{self.words(1, 6)}</title></head><body {MARK}="1">{body}</body></html>'


def labelled_pages(n: int, seed: int = 11) -> list[str]:
    maker = Maker(seed)
    return [maker.page() for _ in range(n)]
