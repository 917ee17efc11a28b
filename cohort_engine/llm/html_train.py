"""Trains the block labeller on generated pages.

``python -m cohort_engine.llm.html_train`` writes the weights. Pages are built from parts (menus, headers, adverts,
notices, sidebars, forms, comments, footers, articles) in many layouts and with many names, with made-up
words; each text of a part carries a mark that says whether it is content, which labels its block.
"""

from __future__ import annotations

import random
from pathlib import Path

import numpy as np

from .html_extract import HIDDEN, STEPS, WIDTH, WORDS, Labeller, blocks, vectors

_SYLLABLES = "the an on er in re th st ed ou tion ing ha de que les ción ar os das und ver keit ung sch é ñ ü la el est pa mi ta ro ne so li ka".split()
_MENU = "Home News About Contact Login Search Products Blog Archive Help Careers Shop Start Inicio Accueil Impressum Kontakt Menu FAQ Forum".split()


class Pages:
    def __init__(self, seed: int) -> None:
        self.r = random.Random(seed)

    def word(self) -> str:
        return "".join(self.r.choices(_SYLLABLES, k=self.r.choice((1, 1, 2, 2, 3))))

    def sentence(self, least: int = 1, most: int = 25) -> str:
        words = [self.word() for _ in range(self.r.randint(least, most))]
        text = " ".join(w + ("," if self.r.random() < 0.06 else "") for w in words).capitalize()
        if self.r.random() < 0.04:  # tables and shouting, in articles as elsewhere
            text = self.r.choice((text.upper(), text.replace(" ", " | "), text.replace(" ", "!! ")))
        return text + self.r.choice((".", ".", ".", ".", "!", "?", ""))

    def prose(self, sentences: int) -> str:
        return " ".join(self.sentence() for _ in range(max(1, sentences)))

    def mark(self, text: str, content: bool) -> str:
        """A private-use character at the front of a block's text holds its label."""
        return ("\ue001" if content else "\ue000") + text

    def named(self, tag: str, names: list[str], inner: str) -> str:
        r = self.r
        if r.random() < 0.12:
            return f"<{tag}>{inner}</{tag}>"
        name = r.choice(names)
        if r.random() < 0.3:
            name += r.choice(("-1", "-area", "_box", "-wrap", " wide", " clearfix", "-inner"))
        if r.random() < 0.2:
            name = r.choice(("x-", "site-", "page-", "c-", "widget ")) + name
        own = f'id="{r.choice(names)}" class="{name}"' if r.random() < 0.2 else f'{r.choice(("class", "class", "id"))}="{name}"'
        return f"<{tag} {own}>{inner}</{tag}>"

    def wrapped(self, inner: str) -> str:
        """Inside several elements whose names say nothing."""
        for _ in range(self.r.choice((1, 2, 3, 6, 12))):
            inner = f"<div{self.r.choice(('', '', ' class=row', ' class=col-md-8', ' class=inner', ' id=wrap', ' class=container'))}>{inner}</div>"
        return inner

    def odd(self) -> str:
        """Markup whose text is left out, not always closed."""
        w = self.word
        return self.r.choice((f"<select><option>{w()}<option selected>{w()}</select>", f"<datalist id=d><option>{w()}<option>{w()}</datalist>", f"<button>{w()}", f"<object data=x><object>{w()}</object>{w()}</object>", f"<noscript>{w()}</noscript>", f"<svg><text>{w()}</text></svg>"))

    def links(self, content: bool, least: int = 2, most: int = 9) -> str:
        r = self.r
        text = lambda: r.choice(_MENU) if r.random() < 0.5 else self.sentence(1, 4).rstrip(".")
        return "<ul>" + "".join(f'<li><a href="/{self.word()}">{self.mark(text(), content)}</a></li>' for _ in range(r.randint(least, most))) + "</ul>"

    def noise(self, kind: str) -> str:
        r, m = self.r, lambda t: self.mark(t, False)
        short, long = lambda: self.prose(r.randint(1, 2)), lambda: self.prose(r.randint(1, 5))
        para = lambda t: f"<p>{m(t)}</p>" if r.random() < 0.5 else m(t)
        if kind == "menu":
            inner = self.links(False) if r.random() < 0.7 else m(" | ".join(f'<a href="#">{r.choice(_MENU)}</a>' for _ in range(r.randint(3, 7))))
            return f"<nav>{inner}</nav>" if r.random() < 0.5 else self.named(r.choice(("div", "ul", "nav")), ["menu", "navbar", "main-nav", "topmenu", "breadcrumb", "breadcrumbs", "pagination", "navigation"], inner)
        if kind == "header":
            inner = r.choice((f"<h1>{m(self.sentence(1, 4))}</h1>", f"<h2>{m(self.sentence(1, 4))}</h2>", m(self.sentence(1, 5)), f'<a href="/">{m(self.sentence(1, 3))}</a>')) + (para(short()) if r.random() < 0.5 else "")
            return f"<header>{inner}</header>" if r.random() < 0.5 else self.named("div", ["header", "masthead", "site-header", "topbar", "logo", "branding"], inner)
        if kind == "advert":
            return self.named(r.choice(("div", "div", "aside", "section")), ["ad", "ads", "advert", "advertisement", "banner", "promo", "sponsored", "sponsor", "adbox", "promotion"], para(short()))
        if kind == "notice":
            t = r.choice(("We use cookies. ", "", "", "Subscribe to our newsletter. ", "Cookies help us. ", "This site uses cookies to improve your visit. ", "Sign up for updates. ")) + short()
            return self.named(r.choice(("div", "section", "aside")), ["cookie", "cookie-banner", "cookie-notice", "notice", "consent", "gdpr", "alert", "newsletter", "popup", "modal", "message", "subscribe", "paywall", "overlay"], para(t) + (f"<button>{self.word()}</button>" if r.random() < 0.5 else ""))
        if kind == "sidebar":
            inner = "".join(r.choice((self.links(False), f"<h3>{m(self.sentence(1, 4))}</h3>", para(long()), f"<h4>{m(self.sentence(1, 3))}</h4>" + self.links(False))) for _ in range(r.randint(1, 3)))
            return f"<aside>{inner}</aside>" if r.random() < 0.5 else self.named(r.choice(("div", "aside", "section")), ["sidebar", "related", "side", "widget", "rail", "recommended", "teaser", "popular", "tags", "share", "social", "trending", "more-stories", "author-bio"], inner)
        if kind == "form":
            fields = "".join(f"<label>{m(self.sentence(1, 3))}</label><input name=q>" for _ in range(r.randint(1, 3)))
            return f'<form action="/s">{r.choice(("", f"<p>{m(short())}</p>", f"<legend>{m(self.word())}</legend>"))}{fields}<button>{self.word()}</button></form>'
        if kind == "comments":
            each = lambda: r.choice((f'<div class="comment"><p>{m(long())}</p></div>', f"<li><b>{m(self.word())}</b><p>{m(long())}</p></li>", f'<div class="reply">{m(long())}</div>', f'<article class="comment"><h4>{m(self.word())}</h4><p>{m(long())}</p></article>'))
            n, head = r.randint(1, 40), r.choice(("h2", "h3", "h3", "h4"))
            title = r.choice(("Comments", "Kommentare", "Responses", f"{n} comments", "Leave a reply", f"{n} replies", f"{n} {self.sentence(1, 4)}", self.sentence(1, 4)))
            inner = (f"<{head}{r.choice(('', ' class=comments-title', ' class=reply-title'))}>{m(title)}</{head}>" if r.random() < 0.7 else "") + "".join(each() for _ in range(r.randint(1, 5)))
            if r.random() < 0.25:  # a thread, answers inside answers
                for _ in range(r.randint(2, 9)):
                    inner = f'<ol{r.choice(("", " class=children", " class=replies"))}><li{r.choice(("", " class=comment", " id=c7"))}>{each()}{inner}</li></ol>'
            return self.named(r.choice(("div", "section", "ol")), ["comments", "comment-list", "commentlist", "discussion", "respond", "disqus", "replies", "reviews", "user-comments"], inner)
        inner = r.choice((m("&copy; 2024 " + short()), para(short()), self.links(False), f"<p>{m('© ' + self.sentence(1, 6))}</p>" + self.links(False), m(f"&copy; {self.word()}.example.net &middot; {long()}")))
        return f"<footer>{inner}</footer>" if r.random() < 0.6 else self.named("div", ["footer", "site-footer", "copyright", "bottom", "legal", "colophon"], inner)

    def article(self) -> str:
        r, m = self.r, lambda t: self.mark(t, True)
        title = self.sentence(1, 10)
        parts = [f"<{h}>{m(title)}</{h}>" for h in (["h1"] if r.random() < 0.85 else ["h2"] if r.random() < 0.5 else [])]
        if parts and r.random() < 0.3:
            own = r.choice(("", ' class="entry-title"', ' class="post-title"', ' class="title"', ' class="headline"', ' id="title"'))
            parts = [parts[0].replace(">", own + ">", 1)]
            if r.random() < 0.5:
                parts = [f"<header{r.choice(('', ' class=entry-header', ' class=article-header'))}>{parts[0]}</header>"]
        bare = r.random() < 0.12
        for k in range(r.choice((1, 1, 2, 3, 4, 5, 6, 8, 12, 20, 40))):
            t = self.prose(r.choice((1, 1, 1, 2, 3, 5, 8)))
            kind = r.random()
            if kind < 0.72:
                if k == 0 and r.random() < 0.3:
                    t = title + " " + t
                if r.random() < 0.15:
                    t = "<b>" + t + ("<br>" if r.random() < 0.5 else "</b>")
                elif r.random() < 0.2:
                    t += f' <a href="/{self.word()}">{self.word()}</a> ' + self.sentence(1, 8)
                parts.append(f"<div>{m(t)}</div>" if bare else f"<p>{m(t)}" + ("</p>" if r.random() < 0.85 else ""))
            elif kind < 0.80:
                parts.append(f"<h{r.choice((2, 3))}>{m(self.sentence(1, 7).rstrip('.'))}</h2>")
            elif kind < 0.87:
                parts.append(r.choice(("<ul>", "<ol>")) + "".join(f"<li>{m(self.sentence(1, 14))}</li>" for _ in range(r.randint(2, 6))) + "</ul>")
            elif kind < 0.92:
                parts.append(f"<blockquote>{r.choice(('<p>', ''))}{m(t)}</blockquote>")
            elif kind < 0.95:
                parts.append("<table>" + "".join(f"<tr><td>{m(self.word())}</td><td>{m(self.sentence(1, 4))}</td></tr>" for _ in range(r.randint(1, 4))) + "</table>")
            elif kind < 0.97:
                parts.append(f"<pre>{m(t)}</pre>")
            else:
                parts.append(self.noise(r.choice(("advert", "sidebar", "notice"))))
        inner = "".join(parts)
        shell = r.random()
        if shell < 0.4:
            return f"<article>{inner}</article>"
        if shell < 0.5:
            return f"<main>{inner}</main>"
        if shell < 0.6:
            return f"<main><article>{inner}</article></main>"
        return self.named(r.choice(("div", "div", "section", "td", "article")), ["content", "main", "article", "post", "entry", "entry-content", "story", "text", "post-body", "article-body", "main-content", "body-text"], inner)

    def shared(self, article: str) -> str:
        """An article and, in the element around it, comments, forms or links that follow."""
        around = "".join([article, *(self.noise(k) for k in ("comments", "form", "sidebar", "menu") if self.r.random() < 0.4)])
        return f"<main>{around}</main>" if self.r.random() < 0.5 else self.named("div", ["main", "content", "container", "site-content", "primary", "column"], around)

    def page(self) -> str:
        r = self.r
        before = [self.noise(k) for k in ("menu", "header", "advert", "notice", "form") if r.random() < 0.45]
        after = [self.noise(k) for k in ("comments", "sidebar", "advert", "form", "menu", "notice", "sidebar") if r.random() < 0.3] + ([self.noise("footer")] if r.random() < 0.8 else [])
        r.shuffle(before)
        middle = "" if r.random() < 0.03 else self.article()
        if r.random() < 0.15:
            before.append(self.odd())
        parts = [self.wrapped(x) if r.random() < 0.12 else x for x in (*before, middle, *after)]
        if r.random() < 0.3:
            parts = [f'<div class="{r.choice(("wrapper", "container", "page", "row", "site"))}">', *parts, "</div>"]
        ends = "</body></html>" if r.random() < 0.9 else ""
        start = "</head><body>" if r.random() < 0.9 else ""
        return f"<!DOCTYPE html><html><head><title>{self.sentence(1, 8)}</title><style>p{{margin:0}}</style>{start}{''.join(parts)}{ends}"


def labelled(page: str) -> tuple[np.ndarray, np.ndarray]:
    """Vectors and labels of a generated page; the marks are taken out before anything is measured."""
    read = blocks(page)
    y = np.array([float("\ue001" in b[3]) for b in read], np.float32)
    clean = [(*b[:3], b[3].replace("\ue001", "").replace("\ue000", "") or ".", b[4]) for b in read]
    return vectors(clean), y


def _sides(rng: np.random.Generator) -> dict[str, np.ndarray]:
    w = {"y": rng.normal(0, 0.2, 2 * HIDDEN), "z": np.zeros(1)}
    for s in "fb":
        w |= {f"{s}x": rng.normal(0, 0.1, (WIDTH, 4 * HIDDEN)), f"{s}h": rng.normal(0, 0.15, (HIDDEN, 4 * HIDDEN)), f"{s}b": np.repeat([0.0, 1.0, 0.0, 0.0], HIDDEN)}
    return {k: v.astype(np.float32) for k, v in w.items()}


def slopes(w: dict[str, np.ndarray], x: np.ndarray, alive: np.ndarray, y: np.ndarray) -> tuple[dict[str, np.ndarray], float]:
    """Loss and its gradient by back-propagation through time, for sequences ``x[step, sequence]``."""
    steps, many, _ = x.shape
    H = HIDDEN
    tape, hidden = {}, {}
    for s in "fb":
        inner, h, c = x @ w[f"{s}x"] + w[f"{s}b"], np.zeros((many, H), np.float32), np.zeros((many, H), np.float32)
        tape[s], hidden[s] = [], np.zeros((steps, many, H), np.float32)
        for t in range(steps) if s == "f" else range(steps - 1, -1, -1):
            g = inner[t] + h @ w[f"{s}h"]
            i, f, o = (1 / (1 + np.exp(-g[:, k * H : (k + 1) * H])) for k in range(3))
            u, on = np.tanh(g[:, 3 * H :]), alive[t][:, None]
            c2 = np.where(on, f * c + i * u, c)
            tc = np.tanh(c2)
            tape[s].append((t, i, f, o, u, c, tc, h, on))
            c, h = c2, np.where(on, o * tc, h)
            hidden[s][t] = h
    both = np.concatenate([hidden["f"], hidden["b"]], 2)
    p = 1 / (1 + np.exp(-(both @ w["y"] + w["z"])))
    n = alive.sum()
    loss = -(np.log(np.where(y > 0, p, 1 - p) + 1e-7) * alive).sum() / n
    dz = (p - y) * alive / n
    grad = {"y": np.einsum("tm,tmh->h", dz, both), "z": dz.sum(keepdims=True).reshape(1)}
    for k, s in enumerate("fb"):
        dout = dz[..., None] * w["y"][k * H : (k + 1) * H]
        dh, dc = np.zeros((many, H), np.float32), np.zeros((many, H), np.float32)
        dinner, dwh = np.zeros((steps, many, 4 * H), np.float32), np.zeros_like(w[f"{s}h"])
        for t, i, f, o, u, c, tc, h, on in reversed(tape[s]):
            dh = dh + dout[t]
            live = np.where(on, dh, 0)
            dct = np.where(on, dc, 0) + live * o * (1 - tc * tc)
            dg = np.concatenate([dct * u * i * (1 - i), dct * c * f * (1 - f), live * tc * o * (1 - o), dct * i * (1 - u * u)], 1)
            dinner[t] = dg
            dwh += h.T @ dg
            dh = np.where(on, dg @ w[f"{s}h"].T, dh)
            dc = np.where(on, dct * f, dc)
        flat = dinner.reshape(-1, 4 * H)
        grad |= {f"{s}x": x.reshape(-1, WIDTH).T @ flat, f"{s}h": dwh, f"{s}b": flat.sum(0)}
    return grad, float(loss)


def train(pages: int = 14000, epochs: int = 4, batch: int = 32, rate: float = 0.006, seed: int = 11) -> dict[str, np.ndarray]:
    maker, rng = Pages(seed), np.random.default_rng(seed)
    data = [d for d in (labelled(maker.page()) for _ in range(pages)) if len(d[0])]
    w = _sides(rng)
    m, v, t = {k: np.zeros_like(x) for k, x in w.items()}, {k: np.zeros_like(x) for k, x in w.items()}, 0
    for epoch in range(epochs):
        order = sorted(range(len(data)), key=lambda k: (len(data[k][0]) + rng.integers(0, 6), k))
        groups = [order[k : k + batch] for k in range(0, len(order), batch)]
        rng.shuffle(groups)
        for group in groups:
            steps = max(len(data[k][0]) for k in group)
            x, alive, y = np.zeros((steps, len(group), WIDTH), np.float32), np.zeros((steps, len(group)), bool), np.zeros((steps, len(group)), np.float32)
            for j, k in enumerate(group):
                size = len(data[k][0])
                x[:size, j], y[:size, j], alive[:size, j] = data[k][0], data[k][1], True
            x[..., :STEPS] *= rng.random((*x.shape[:2], STEPS), np.float32) > 0.05  # names that a page lacks
            x[..., STEPS : STEPS + WORDS] *= rng.random((*x.shape[:2], WORDS), np.float32) > 0.3  # and words
            grad, _ = slopes(w, x, alive, y)
            t += 1
            step = rate * (0.4**epoch)
            for k, g in grad.items():
                m[k] = 0.9 * m[k] + 0.1 * g
                v[k] = 0.999 * v[k] + 0.001 * g * g
                w[k] = (w[k] - step * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)).astype(np.float32)
    return w


def accuracy(model: Labeller, pages: int = 400, seed: int = 99) -> float:
    """Share of blocks of unseen generated pages that get their label."""
    maker = Pages(seed)
    data = [labelled(maker.page()) for _ in range(pages)]
    right = sum(((p >= 0.5) == (y > 0)).sum() for p, (_, y) in zip(model.label([x for x, _ in data]), data, strict=True))
    return float(right / sum(len(y) for _, y in data))


if __name__ == "__main__":
    weights = train()
    print(accuracy(Labeller(weights)))
    np.savez_compressed(Path(__file__).with_name("html_weights.npz"), **{k: x.astype(np.float16) for k, x in weights.items()})
