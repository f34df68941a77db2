"""Labelled pages to learn content weights from.

Pages of many layouts are made from a seed; every page comes with the list of
its content blocks.  Layouts differ in their elements, order, nesting and
carelessness (unclosed paragraphs, missing ends).  Class names and ids are
random strings, so nothing can be learnt from them.
"""

from __future__ import annotations

import random

#: Elements that sites use for what is not content, by kind.
_TAGS = {"advert": ["div", "aside", "section", "ins"], "menu": ["nav", "ul", "div", "menu"], "header": ["header", "div"], "footer": ["footer", "div"], "sidebar": ["aside", "div", "section"], "notice": ["div", "section", "dialog"], "form": ["form", "div"], "comments": ["section", "div", "ol", "article"], "share": ["div", "ul"]}
_ROLES = {"menu": "navigation", "header": "banner", "footer": "contentinfo", "sidebar": "complementary", "form": "search", "notice": "alert dialog alertdialog status"}


class _Maker:
    def __init__(self, rng: random.Random):
        self.rng = rng
        self.n = 0

    def words(self, lo: int, hi: int) -> str:
        self.n += 1
        return " ".join(["".join(self.rng.choice("abcdeimnorstu") for _ in range(self.rng.randint(2, 8))) for _ in range(self.rng.randint(lo, hi))] + [f"w{self.n}"])

    def named(self) -> str:
        """No attribute, or a class or id that tells nothing."""
        if self.rng.random() < 0.3:
            return ""
        return f' {self.rng.choice(["class", "class", "id"])}="{"".join(self.rng.choice("bcdfghjklmnpqrstvwxyz-") for _ in range(self.rng.randint(3, 12)))}"'

    def boilerplate(self, kind: str) -> str:
        rng = self.rng
        tag = rng.choice(_TAGS[kind])
        attrs = self.named()
        if kind in _ROLES and rng.random() < 0.15:
            attrs += f' role="{rng.choice(_ROLES[kind].split())}"'
        if kind in ("menu", "share"):
            items = "".join(f'<li><a href="/{i}">{self.words(0, 2)}</a></li>' for i in range(rng.randint(2, 7)))
            inner = items if tag in ("ul", "menu") else rng.choice([f"<ul>{items}</ul>", items.replace("<li>", "").replace("</li>", " ")])
        elif kind == "form":
            inner = f'<label>{self.words(0, 3)}</label><input name="q"><button>{self.words(0, 2)}</button>' + (f"<p>{self.words(3, 15)}</p>" if rng.random() < 0.5 else "")
        elif kind == "comments":
            shape = rng.choice(["<div{}><p>{}</p></div>", "<li{}><p>{}</p></li>", "<p{}>{}</p>", "<article{}><p>{}</p></article>"])
            inner = (f"<h3>{self.words(0, 3)}</h3>" if tag != "ol" else "") + "".join(shape.format(self.named(), self.words(3, 40)) for _ in range(rng.randint(1, 4)))
        else:
            inner = rng.choice([self.words(1, 30), f"<p>{self.words(1, 40)}</p>", f"<h4>{self.words(0, 4)}</h4><p>{self.words(3, 25)}</p>", f'<a href="/x">{self.words(0, 6)}</a>', f"<ul><li><a href='#'>{self.words(0, 5)}</a></li><li>{self.words(0, 5)}</li></ul>"])
        if tag in ("aside", "footer", "form", "header", "dialog", "nav") and rng.random() < 0.25:  # what these hold is no content, however long
            inner += "".join(f"<p>{self.words(10, 70)}</p>" for _ in range(rng.randint(1, 4)))
        return f"<{tag}{attrs}>{inner}</{tag}>"

    def content(self, blocks: list[str]) -> str:
        rng = self.rng

        def put(lo: int, hi: int) -> str:
            blocks.append(self.words(lo, hi))
            return blocks[-1]

        def paragraph() -> str:
            said = put(0, 60)
            if rng.random() < 0.1:  # some of its words are a link
                first, _, rest = said.partition(" ")
                said = f'<a href="/y">{first}</a> {rest}' if rest else said
            return f"<p{self.named() if rng.random() < 0.1 else ''}>{said}" + ("</p>" if rng.random() < 0.8 else "")

        parts = [f"<h1>{put(0, 9)}</h1>"] if rng.random() < 0.95 else [paragraph()]
        if rng.random() < 0.15:
            parts = [f"<header>{parts[0]}</header>"]
        for _ in range(rng.randint(1, 9)):
            form = rng.random()
            if form < 0.6:
                parts.append(paragraph())
            elif form < 0.66:
                parts.append(f"<p><b>{put(0, 20)}<br>")
            elif form < 0.74:
                level = rng.randint(2, 4)
                parts.append(f"<h{level}>{put(0, 8)}</h{level}>")
            elif form < 0.82:
                parts.append(f"<ul><li>{put(1, 12)}</li><li>{put(1, 12)}</li></ul>")
            elif form < 0.87:
                parts.append(f"<blockquote>{put(2, 30)}</blockquote>" if rng.random() < 0.5 else f"<blockquote><p>{put(2, 30)}</p></blockquote>")
            elif form < 0.92:
                rows = "".join(f"<tr><td>{put(0, 6)}</td><td>{put(0, 6)}</td></tr>" for _ in range(rng.randint(1, 4)))
                parts.append(f"<table>{rows}</table>")
            elif form < 0.95:
                parts.append(f'<figure><img src="x.png"><figcaption>{put(1, 15)}</figcaption></figure>')
            elif form < 0.97:
                parts.append(f"<section><h2>{put(0, 8)}</h2>" + "".join(f"<p>{put(20, 70)}</p>" for _ in range(rng.randint(2, 4))) + "</section>")
            else:
                parts.append(f"<pre>{put(2, 20)}</pre>")
            if rng.random() < 0.12:
                parts.append(self.boilerplate(rng.choice(["advert", "sidebar", "notice", "form", "share"])))
        return "".join(parts)


def labelled_pages(count: int = 700, seed: int = 11) -> list[tuple[str, list[str]]]:
    """(html, content blocks) pairs; the same for the same arguments."""
    rng = random.Random(seed)
    pages = []
    for _ in range(count):
        make = _Maker(rng)
        blocks: list[str] = []
        body = make.content(blocks)
        shape = rng.random()
        if shape < 0.5:
            body = f"<article{make.named()}>{body}" + (make.boilerplate("comments") if rng.random() < 0.15 else "") + "</article>"
            if rng.random() < 0.3:
                body = f"<main>{body}</main>"
        elif shape < 0.65:
            body = f"<main>{body}</main>"
        elif shape < 0.88:
            body = f"<div{make.named()}>{body}</div>"
        elif shape < 0.92:
            body = f"<table><tr><td>{make.boilerplate('menu')}</td><td>{body}</td></tr></table>"
        before = [make.boilerplate(k) for k in rng.sample(["menu", "header", "advert", "notice", "form", "share"], rng.randint(0, 4))]
        after = [make.boilerplate(k) for k in rng.sample(["footer", "comments", "sidebar", "advert", "share", "form"], rng.randint(0, 4))]
        inner = f"{''.join(before)}{body}{''.join(after)}"
        if rng.random() < 0.25:  # a wrapper around everything
            inner = f"<div{make.named()}>{inner}</div>"
        title = f"<head><title>{make.words(1, 8)}</title></head>" if rng.random() < 0.8 else ""
        pages.append((f"<html>{title}<body>{inner}" + ("</body></html>" if rng.random() < 0.9 else ""), blocks))
    pages += [(text, [text]) for text in (_Maker(rng).words(1, 30) for _ in range(count // 20))]
    return pages
