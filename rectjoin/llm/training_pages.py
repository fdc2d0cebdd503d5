"""Labelled web pages, written by rule: the training data of the page model.

Every page has an article between some of the things that aren't: menus, headers, footers, sidebars, notices,
adverts, forms and reader comments, in many layouts and names, with the sloppy markup that pages have. A
block's label is told by a marker word that is put in its text while the page is written and taken out before.
"""

from __future__ import annotations

import random
from collections.abc import Callable, Iterator

SYLLABLES = "ba ce di fo gu ha je ki lo mu na pe ri so tu va we xi yo zu an er in on th st le re de la".split()
NOT_MAIN = {
    "nav": "nav menu navbar navigation topnav breadcrumb breadcrumbs mainmenu submenu",
    "header": "header masthead banner topbar branding sitehead",
    "footer": "footer bottom colophon sitefooter copyright legal",
    "aside": "sidebar aside related widget recommended trending rail more popular",
    "ad": "ad ads advert advertisement sponsor sponsored promo banner-ad dfp",
    "notice": "cookie consent notice gdpr alert popup modal newsletter subscribe disclaimer paywall",
    "comments": "comments comment replies discussion disqus respond responses reader",
    "social": "share social sharing follow tags meta toolbar",
    "form": "search form login signup contact",
}
MAIN = "article content post entry main story body text article-body post-content entry-content maincontent".split()


class Writer:
    def __init__(self, rng: random.Random):
        self.rng, self.kinds = rng, {}

    def words(self, n: int) -> str:
        r = self.rng
        out = ["".join(r.choice(SYLLABLES) for _ in range(r.randint(1, 4))) for _ in range(n)]
        return " ".join(out)

    def text(self, main: bool, low: int, high: int, stop: bool = True) -> str:
        r, out, left = self.rng, [], self.rng.randint(low, high)
        while left > 0:
            k = min(left, r.randint(3, 18))
            s = self.words(k).capitalize()
            if r.random() < 0.25:
                s = " ".join(w + r.choice(("***", "###", "%%%", "!!", " |", ",")) for w in s.split())
            out.append(s + ("." if stop or left > k else ""))
            left -= k
        s = " ".join(out)
        s = s.upper() if r.random() < 0.03 else s
        self.kinds[" ".join(s.split())] = main
        return s

    def attr(self, names: str | list[str]) -> str:
        r = self.rng
        names = names.split() if isinstance(names, str) else names
        if r.random() < 0.2:
            return ""
        pick = r.choice(names) + (r.choice(("", "", "-wrap", "-box", "_inner", " clearfix", "-list", " col")))
        return f' {r.choice(("class", "class", "id"))}="{pick}"'

    def links(self, n: int, in_list: bool) -> str:
        item = lambda: f'<a href="/{self.words(1)}">{self.text(False, 1, 4, False)}</a>'
        return "<ul>" + "".join(f"<li>{item()}{'</li>' if self.rng.random() < 0.8 else ''}" for _ in range(n)) + "</ul>" if in_list else " ".join(f"<div>{item()}</div>" for _ in range(n))

    def other(self, kind: str) -> str:
        r, names = self.rng, NOT_MAIN[kind]
        tag = {"nav": ("nav", "nav", "div", "ul"), "header": ("header", "header", "div"), "footer": ("footer", "footer", "div"), "aside": ("aside", "aside", "div"), "form": ("form", "form", "div"), "comments": ("section", "div", "div", "ol")}.get(kind, ("div", "div", "section", "p"))
        tag, named = r.choice(tag), self.attr(names)
        if tag in ("div", "section", "p", "ul", "ol") and not named:
            named = f' class="{r.choice(names.split())}"'
        if kind == "nav":
            inner = self.links(r.randint(2, 9), r.random() < 0.8)
        elif kind == "header":
            inner = (f"<h1>{self.text(False, 1, 4, False)}</h1>" if r.random() < 0.4 else f"<div>{self.text(False, 1, 5, False)}</div>") + (self.links(3, True) if r.random() < 0.5 else "")
        elif kind == "footer":
            inner = f"{'&copy; ' if r.random() < 0.7 else ''}{self.text(False, 2, 14, r.random() < 0.6)}" + (self.links(r.randint(1, 5), r.random() < 0.5) if r.random() < 0.4 else "")
            inner = inner if r.random() < 0.5 else f"<p>{inner}</p>"
        elif kind == "aside":
            inner = f"<h3>{self.text(False, 1, 5, False)}</h3>" + (self.links(r.randint(2, 6), True) if r.random() < 0.6 else f"<p>{self.text(False, 5, 50)}</p>")
        elif kind == "comments":
            inner = f"<h3>{self.text(False, 1, 3, False)}</h3>" + "".join(f"<{r.choice(('div', 'li', 'article', 'p'))} class=\"comment\"><b>{self.text(False, 1, 2, False)}</b><p>{self.text(False, 3, 60)}</p></div>" for _ in range(r.randint(1, 5)))
        elif kind == "form":
            inner = f'<label>{self.text(False, 1, 4, False)}</label><input type="text" placeholder="x"><p>{self.text(False, 2, 14)}</p>'
        elif kind == "social":
            inner = self.text(False, 1, 5, False) + self.links(r.randint(1, 4), r.random() < 0.5)
        else:
            inner = self.text(False, 4, 40)
            inner = inner if r.random() < 0.5 else f"<p>{inner}</p>"
        return f"<{tag}{named}>{inner}</{tag}>"

    def article(self) -> str:
        r, out = self.rng, []
        title = self.text(True, 2, 14, r.random() < 0.3)
        out.append(f"<h1>{title}</h1>")
        if r.random() < 0.4:
            out.append(f"<p><b>{self.text(True, 2, 18)}<br>")
        for _ in range(r.randint(1, 9)):
            roll = r.random()
            if roll < 0.12:
                out.append(f"<h{r.randint(2, 4)}>{self.text(True, 1, 9, False)}</h2>")
            if roll > 0.93:
                out.append("<ul>" + "".join(f"<li>{self.text(True, 3, 20, r.random() < 0.5)}</li>" for _ in range(r.randint(2, 4))) + "</ul>")
            elif roll > 0.89:
                out.append(f"<blockquote>{self.text(True, 5, 50)}</blockquote>")
            elif roll > 0.86:
                out.append("<table>" + "".join(f"<tr><td>{self.text(True, 1, 4, False)}</td><td>{self.text(True, 1, 4, False)}</td></tr>" for _ in range(r.randint(2, 3))) + "</table>")
            elif roll > 0.83:
                out.append(f"<pre>{self.text(True, 4, 20, False)}</pre>")
            else:
                low, high = r.choice(((1, 4), (3, 12), (10, 60), (30, 140)))
                out.append(f"<{r.choice(('p', 'p', 'p', 'p', 'div'))}>{self.text(True, low, high, r.random() < 0.8)}" + ("</p>" if r.random() < 0.9 else ""))
            if r.random() < 0.06:
                out.append(self.other(r.choice(("ad", "aside", "social", "notice"))))
        tag = r.choice(("article", "article", "article", "main", "div", "section"))
        named = self.attr(MAIN)
        if tag in ("div", "section") and not named:
            named = f' class="{r.choice(MAIN)}"'
        body = f"<{tag}{named}>{''.join(out)}</{tag}>"
        return f"<main>{body}</main>" if r.random() < 0.15 else body

    def page(self) -> str:
        r = self.rng
        before = [self.other(k) for k in ("notice", "header", "nav", "form", "ad", "social") if r.random() < 0.45]
        after = [self.other(k) for k in ("social", "ad", "aside", "comments", "nav", "form", "notice", "footer") if r.random() < 0.45]
        r.shuffle(before)
        wrap = r.random() < 0.3
        return f"<!DOCTYPE html><html><head><title>{self.words(4)}</title><script>var a='</p>';</script></head><body>{'<div id=page>' if wrap else ''}{''.join(before)}{self.article()}{''.join(after)}{'</div>' if wrap else ''}</body></html>"


def labelled_pages(n: int, seed: int) -> Iterator[tuple[str, Callable[[str], int]]]:
    """Pages with a function that tells the label of a block of theirs."""
    for k in range(n):
        writer = Writer(random.Random(seed * 1_000_003 + k))
        html, kinds = writer.page(), writer.kinds

        def label(text: str, kinds=kinds) -> int:
            if text in kinds:
                return int(kinds[text])
            return int(any(main and len(t) > 3 and t in text for t, main in kinds.items()))

        yield html, label
