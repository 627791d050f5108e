"""Training of the block labeller on made-up pages: ``python -m cloudlattice.llm.html_training``.

Pages are drawn from a grammar of layouts: containers with usual and unusual tags
and names, main text of paragraphs, headings, lists, quotes and tables, and around
it menus, headers, footers, sidebars, notices, adverts, forms and reader comments.
Words are random syllables in both kinds, with some telling words in the second.
"""

from __future__ import annotations

import random

import numpy as np

from cloudlattice.llm.html_blocks import blocks
from cloudlattice.llm.html_model import Params, gradients, initial, inputs, probabilities, save

# fixed values: names that pages give their parts
SIDE = {
    "nav": (["nav", "div", "ul", "header"], "nav navbar menu navigation breadcrumb breadcrumbs topbar links tabs pagination pager toc sitemap skip".split()),
    "header": (["header", "div"], "header masthead banner top branding logo site-header tagline".split()),
    "footer": (["footer", "div"], "footer bottom copyright colophon legal site-footer credits imprint".split()),
    "aside": (["aside", "div", "section"], "sidebar aside widget related recommended trending popular more-stories promo rail tags share social author-box newsletter".split()),
    "notice": (["div", "section", "p"], "cookie consent notice gdpr alert banner popup modal overlay subscribe paywall privacy message".split()),
    "ad": (["div", "aside", "section", "ins"], "ad ads advert advertisement sponsored sponsor promo dfp adslot banner-ad".split()),
    "form": (["form", "div"], "form search login signup subscribe contact newsletter register".split()),
    "comments": (["div", "section", "ol", "aside"], "comments comment comment-list discussion replies responses thread disqus reply respond".split()),
}
MAIN = "content article post entry story body text main article-body post-content entry-content story-body page-content hentry prose markdown".split()
TELLING = {
    "nav": "home about contact next previous menu news archive login".split(),
    "header": "welcome search menu sign in".split(),
    "footer": "© copyright 2024 rights reserved terms privacy powered · contact".split(),
    "aside": "related popular share follow recommended more tags tweet".split(),
    "notice": "cookies accept consent policy subscribe we use agree".split(),
    "ad": "advertisement sponsored buy now offer sale click deal".split(),
    "form": "email password submit search name subscribe".split(),
    "comments": "reply said says posted comment likes ago user".split(),
}


class Pages:
    def __init__(self, seed: int):
        self.r = random.Random(seed)
        self.syllables = [self.r.choice("bcdfghklmnprstvwz") + self.r.choice("aeiouäéèíóöü") + self.r.choice(["", "n", "r", "s", "nd", "th"]) for _ in range(120)]

    def words(self, n: int, telling: list[str] = (), share: float = 0.0) -> str:
        r, out = self.r, []
        for _ in range(n):
            out.append(r.choice(telling) if telling and r.random() < share else "".join(r.choice(self.syllables) for _ in range(r.randint(1, 3))))
            if r.random() < 0.1:
                out[-1] += r.choice(",.;:") if r.random() < 0.9 else "!"
        style = r.random()
        if style < 0.06:
            return r.choice([" | ", " / ", " - ", " > "]).join(out)
        if style < 0.12:
            return " ".join(w + r.choice(["***", "%%%", "###", "&&&", "$$$", "!!!"]) for w in out)
        if style < 0.18:
            return " ".join(w if r.random() < 0.6 else str(r.randint(0, 10**9)) for w in out)
        if style < 0.22:
            return " ".join(out).upper() + r.choice(["", "!!", "..."])
        if style < 0.26:
            return " ".join([r.choice(out)] * len(out))
        return " ".join(out).capitalize()

    def end(self) -> str:
        return self.r.choice([".", ".", ".", "", "", "!", "?", ":"])

    def attributes(self, names: list[str], likely: float) -> str:
        r = self.r
        if r.random() > likely:
            return ""
        value = r.choice(names) + (f" {r.choice(['wrap', 'box', 'row', 'col', 'inner', 'block'])}" if r.random() < 0.2 else "") + (f"-{r.randint(1, 9)}" if r.random() < 0.1 else "")
        return f' {r.choice(["class", "class", "id"])}="{value}"'

    def side(self, kind: str) -> str:
        r, (tags, names) = self.r, SIDE[kind]
        tag = r.choice(tags) if r.random() < 0.7 else tags[0]
        plain = tag in ("nav", "footer", "aside", "header", "form")
        telling, inner = TELLING[kind], ""
        for _ in range(r.randint(1, 8 if kind in ("nav", "aside", "comments") else 3)):
            text = self.words(r.randint(1, 4) if kind == "nav" else r.randint(1, 30 if kind in ("comments", "notice", "ad", "footer", "aside") else 8), telling, r.choice([0, 0, 0.1, 0.3])) + (self.end() if kind != "nav" else "")
            link = f'<a href="/{r.randint(1, 999)}">{text}</a>'
            shape = r.random()
            if kind == "nav" or (kind in ("aside", "header", "footer") and shape < 0.4):
                inner += f"<li>{link}</li>" if r.random() < 0.7 else link + r.choice([" ", " | ", "<br>"])
            elif kind == "form":
                inner += f"<label>{text}</label><input name=q>"
            elif shape < 0.6:
                inner += f"<p>{text}</p>"
            elif shape < 0.8:
                inner += f"<div>{text}</div>" if kind != "comments" else f'<div{self.attributes(names, 0.7)}><b>{self.words(1)}</b><p>{text}</p></div>'
            else:
                inner += text + " "
        if "<li>" in inner and tag not in ("ul", "ol"):
            inner = f"<ul>{inner}</ul>"
        if kind in ("aside", "comments", "form", "header") and r.random() < 0.4:
            inner = f"<h{r.randint(1, 4)}>{self.words(r.randint(1, 4), telling, 0.3)}</h3>" + inner
        return f"<{tag}{self.attributes(names, 0.45 if plain else 1.0)}>{inner}</{tag}>"

    def main(self) -> str:
        r, out = self.r, []
        mark = "\x01"  # marks main text until the page is read back
        if r.random() < 0.8:
            out.append(f"<h1>{mark}{self.words(r.randint(2, 14))}</h1>")
        for _ in range(r.choice([1, 2, 3, 5, 8, 12, 20])):
            text = self.words(r.choice([2, 5, 10, 25, 50, 120])) + self.end()
            if r.random() < 0.15:
                text += f' <a href="/x">{self.words(2)}</a> {self.words(4)}'
            shape = r.random()
            if shape < 0.72:
                out.append(r.choice([f"<p>{mark}{text}</p>", f"<p>{mark}{text}", f"<p><b>{mark}{text}<br>"]) if r.random() < 0.35 else f"<p>{mark}{text}</p>")
            elif shape < 0.8:
                out.append(f"<h{r.randint(2, 4)}>{mark}{self.words(r.randint(1, 8))}</h2>")
            elif shape < 0.87:
                out.append("<ul>" + "".join(f"<li>{mark}{self.words(r.randint(2, 20))}</li>" for _ in range(r.randint(1, 5))) + "</ul>")
            elif shape < 0.91:
                out.append(f"<blockquote>{mark}{text}</blockquote>")
            elif shape < 0.94:
                out.append(f"<table><tr><td>{mark}{self.words(3)}</td><td>{mark}{self.words(3)}</td></tr></table>")
            elif shape < 0.96:
                out.append(f"<pre>{mark}{text}</pre>")
            else:
                out.append(f"<div>{mark}{text}</div>")
            if r.random() < 0.04:
                out.append(self.side(r.choice(["ad", "aside", "notice"])))
        body = "".join(out)
        shape = r.random()
        if shape < 0.45:
            body = f"<article{self.attributes(MAIN, 0.4)}>{body}</article>"
        elif shape < 0.6:
            body = f"<main>{body}</main>" if r.random() < 0.5 else f"<main><article>{body}</article></main>"
        elif shape < 0.9:
            body = f"<div{self.attributes(MAIN, 1.0)}>{body}</div>"
        return body

    def page(self) -> str:
        r = self.r
        before = [k for k in ("notice", "header", "nav", "ad", "form", "aside") if r.random() < (0.75 if k == "nav" else 0.35)]
        after = [k for k in ("ad", "aside", "comments", "form", "notice", "footer") if r.random() < (0.8 if k == "footer" else 0.35)]
        r.shuffle(before)
        page = "".join(map(self.side, before)) + self.main() + "".join(map(self.side, after))
        if r.random() < 0.3:
            page = f'<div{self.attributes(["page", "wrapper", "container", "site", "app", "layout"], 1.0)}>{page}</div>'
        return f"<html><head><title>{self.words(4)}</title></head><body>{page}</body></html>"


def examples(n: int, seed: int) -> tuple[list[list[tuple]], list[list[int]]]:
    made = Pages(seed)
    x, y = [], []
    for _ in range(n):
        found = blocks(made.page())
        y.append([int("\x01" in b.text) for b in found])
        for b in found:
            b.text = b.text.replace("\x01", "")
        x.append([inputs(b) for b in found])
    return x, y


def train(pages: int = 9000, rounds: int = 6, seed: int = 1, rate: float = 0.006) -> Params:
    """Adam over batches of 32 pages."""
    x, y = examples(pages, seed)
    p, rng = initial(seed), np.random.default_rng(seed)
    first, second = ({k: np.zeros_like(v) for k, v in p.items()} for _ in range(2))
    step = 0
    for _ in range(rounds):
        order = sorted(range(pages), key=lambda k: (len(x[k]) // 8, rng.random()))
        batches = [order[i : i + 32] for i in range(0, pages, 32)]
        rng.shuffle(batches)
        for batch in batches:
            step += 1
            # words and measures are hidden now and then, so that no label hangs on them alone
            hidden = [[(path, tail, [] if rng.random() < 0.3 else words, [0.0] * len(m) if rng.random() < 0.2 else m) for path, tail, words, m in x[k]] for k in batch]
            _, g = gradients(p, hidden, [y[k] for k in batch])
            g["word"] += 1e-4 * p["word"]
            for k in p:
                gk = np.clip(g[k], -1, 1)
                first[k] = 0.9 * first[k] + 0.1 * gk
                second[k] = 0.999 * second[k] + 0.001 * gk**2
                p[k] -= rate * (0.3 if step > 0.7 * rounds * len(batches) else 1) * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
    return p


def accuracy(p: Params, pages: int = 500, seed: int = 99) -> float:
    x, y = examples(pages, seed)
    got = probabilities(p, x)
    right = [int(a >= 0.5) == b for q, t in zip(got, y, strict=True) for a, b in zip(q, t, strict=True)]
    return float(np.mean(right))


if __name__ == "__main__":
    model = train()
    print(f"held-out block accuracy {accuracy(model):.4f}")
    save(model)
