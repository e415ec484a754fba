"""Trains the block labeller from pages drawn by rule: ``python -m backtrail.llm.html_training``.

Pages vary in their frame (semantic tags, or divisions with telling or bare class names), in what surrounds the article (menus,
notices, adverts, side columns, forms, related links, share buttons, reader comments, footers) and in what it holds
(headings, paragraphs, lists, quotations, tables, captions).  Every block knows whether it belongs to the article.
"""

from __future__ import annotations

import random

import numpy as np

from backtrail.llm.html_extract import PATH_SIZE, PROPORTIONS, WEIGHTS, WORD_SIZE, Labeller, Reader, blocks, reversal

HIDDEN, PAGES, EPOCHS, BATCH, RATE = 20, 6000, 14, 40, 0.01
MARK = "\x02"  # begins every block of the article in training pages

_SYLLABLES = {
    "en": "the and er on re ing ly tion ed is to of in that th ha ou st ea or".split(),
    "es": "que de la ción el os ar men te ra do ía ue co ja bo es ci".split(),
    "de": "der die und en ung lich ein sch heit ver ge be zu au ch ö ä".split(),
    "fr": "le la de et tion eau oir que ment ou ai é re aux en un".split(),
}


class Writer:
    """Draws pages; blocks of the article begin with the mark."""

    def __init__(self, seed: int):
        self.rng = random.Random(seed)

    def word(self, lang: str) -> str:
        return "".join(self.rng.choice(_SYLLABLES[lang]) for _ in range(self.rng.randint(1, 4)))

    def words(self, lang: str, low: int, high: int) -> str:
        return " ".join(self.word(lang) for _ in range(self.rng.randint(low, high)))

    def prose(self, lang: str, most: int) -> str:
        rng, out = self.rng, []
        if rng.random() < 0.02:  # one word again and again
            return " ".join([self.word(lang).capitalize()] * rng.choice((3, 9, 40, 300)))
        for _ in range(rng.randint(1, most)):
            out.append(self.words(lang, 1, 22).capitalize() + rng.choice(".....!?:"))
        text = " ".join(out)
        return text + rng.choice(("", "", "", "", "\n" + self.words(lang, 1, 6).capitalize() + "."))

    def inline(self, text: str) -> str:
        parts = text.split(" ")
        if len(parts) > 4 and self.rng.random() < 0.25:
            i = self.rng.randrange(len(parts))
            tag = self.rng.choice(("a href='/x'", "b", "em", "span", "strong"))
            parts[i] = f"<{tag}>{parts[i]}</{tag.split(' ')[0]}>"
        return " ".join(parts)

    def lang(self) -> str:
        return self.rng.choice(("en", "en", "es", "de", "fr"))

    def links(self, low: int, high: int) -> str:
        lang = self.lang()
        return "<ul>" + "".join(f"<li><a href='/{i}'>{self.words(lang, 1, 4)}</a></li>" for i in range(self.rng.randint(low, high))) + "</ul>"

    def box(self, tags: tuple, names: tuple, inner: str) -> str:
        rng = self.rng
        tag = rng.choice(tags)
        name = "" if tag != "div" and rng.random() < 0.6 else f' {rng.choice(("class", "class", "id"))}="{rng.choice(names)}"'
        return f"<{tag}{name}>{inner}</{tag}>"

    def some(self, most: int) -> str:
        lang, rng = self.lang(), self.rng
        text = self.prose(lang, most)
        return rng.choice((text, f"<p>{text}</p>", f"<p>{text}</p><p>{self.prose(lang, 2)}</p>", f"<h3>{self.words(lang, 1, 4)}</h3><p>{text}</p>"))

    # what surrounds an article
    def around(self, before: bool) -> str:
        rng, pick = self.rng, self.rng.choice
        nav = lambda: self.box(("nav", "nav", "div"), ("nav", "menu", "main-menu", "navbar", "navigation", "topnav", "breadcrumbs", "breadcrumb", "links"), self.links(2, 9))
        ad = lambda: self.box(("div", "div", "aside", "section"), ("ad", "ads", "advert", "advertisement", "sponsored", "promo", "banner", "ad-slot", "sponsor"), self.some(3))
        notice = lambda: self.box(("div", "section", "div"), ("cookie", "cookie-notice", "notice", "consent", "cookies", "alert", "gdpr", "cookie-banner", "popup", "modal"), self.some(2) + pick(("", "<button>OK</button>")))
        side = lambda: self.box(("aside", "aside", "div"), ("sidebar", "side", "widget", "aside", "related", "rail", "recommended", "popular", "trending"), pick((self.some(3), f"<h3>{self.words(self.lang(), 1, 3)}</h3>" + self.links(2, 6), self.links(2, 6) + self.some(2))))
        form = lambda: pick(("<form>{}</form>", '<form class="search">{}</form>', '<div class="newsletter"><form>{}</form></div>', '<div class="subscribe">{}</div>', '<form id="login">{}</form>')).format(f"<label>{self.words(self.lang(), 1, 4)}</label><input name='q'>" + pick(("", f"<p>{self.prose(self.lang(), 2)}</p>", f"<select><option>{self.words(self.lang(), 1, 2)}<option>{self.words(self.lang(), 1, 2)}</select>")) + f"<button>{self.words(self.lang(), 1, 2)}</button>")
        share = lambda: self.box(("div", "ul"), ("share", "social", "sharing", "tags", "meta", "toolbar"), "".join(f"<a href='#'>{self.word('en')}</a> " for _ in range(rng.randint(2, 5))))

        def comment() -> str:
            head = pick(("", f"<span class='user'>{self.word(self.lang())}</span>", f"<h4>{self.words(self.lang(), 1, 2)}</h4>", f"<div class='author'>{self.word('en')}</div>"))
            return self.box(("div", "li", "article", "div", "p"), ("comment", "comment-body", "reply", "post-comment", "user-comment"), head + pick(("{}", "<p>{}</p>")).format(self.prose(self.lang(), 4)))

        comments = lambda: self.box(("section", "div", "div", "ol"), ("comments", "comment-list", "discussion", "responses", "reader-comments", "disqus", "replies"), pick(("", f"<h2>{self.words('en', 1, 2)}</h2>", f"<h3>{self.words('en', 1, 2)}</h3>")) + "".join(comment() for _ in range(rng.randint(1, 6))))
        footer = lambda: self.box(("footer", "footer", "div"), ("footer", "site-footer", "foot", "copyright", "bottom", "legal"), pick((f"&copy; {self.word('en')}.example.net &middot; {self.prose(self.lang(), 2)}", self.some(2), f"&copy; 20{rng.randint(10, 30)} {self.words('en', 1, 3)}" + self.links(1, 5))))
        header = lambda: self.box(("header", "header", "div"), ("header", "site-header", "top", "masthead", "logo", "branding", "topbar"), pick((self.words(self.lang(), 1, 4), f"<h1>{self.words(self.lang(), 1, 4)}</h1>", f"<a href='/'>{self.word('en')}</a><p>{self.prose(self.lang(), 1)}</p>", f"<h2>{self.words('en', 1, 3)}</h2>" + self.links(2, 5))))
        drawn = [f() for f, odds in ((header, 0.45), (notice, 0.3), (nav, 0.8), (form, 0.2), (ad, 0.5), (side, 0.2), (share, 0.1)) if rng.random() < odds] if before else [f() for f, odds in ((share, 0.2), (ad, 0.25), (side, 0.4), (form, 0.25), (comments, 0.45), (nav, 0.15), (notice, 0.15), (footer, 0.85)) if rng.random() < odds]
        if rng.random() < 0.3:
            rng.shuffle(drawn)
        return pick(("", "\n")).join(drawn)

    def article(self) -> str:
        rng, pick, lang = self.rng, self.rng.choice, self.lang()
        out, most = [], pick((1, 2, 4, 12, 30, 80))
        title = pick((self.words(lang, 3, 12).capitalize(), self.prose(lang, 1), self.words(lang, 1, 3)))
        if rng.random() < 0.9:
            out.append(f"<h1>{MARK}{title}</h1>")
        if rng.random() < 0.5:
            out.append(f"<p><b>{MARK}{self.inline(self.prose(lang, most))}<br>")
        for _ in range(pick((0, 1, 2, 4, 8, 16)) + (len(out) < 2)):
            out.append(f"<p>{MARK}{self.inline(self.prose(lang, pick((1, most))))}</p>")
            if rng.random() < 0.12:
                out.append(pick((f"<h2>{MARK}{self.words(lang, 1, 6)}</h2>", f"<h3>{MARK}{self.words(lang, 1, 6)}</h3>", f"<blockquote>{MARK}{self.prose(lang, 3)}</blockquote>", "<ul>" + "".join(f"<li>{MARK}{self.words(lang, 2, 12)}</li>" for _ in range(rng.randint(2, 5))) + "</ul>", f"<pre>{MARK}{self.words(lang, 3, 20)}</pre>", "<table>" + "".join(f"<tr><td>{MARK}{self.word(lang)}<td>{MARK}{rng.randint(1, 999)}" for _ in range(rng.randint(1, 4))) + "</table>", f"<figure><img src='x'><figcaption>{MARK}{self.words(lang, 3, 10)}</figcaption></figure>")))
            if rng.random() < 0.02:  # a passage that repeats
                again = pick((f"<p>{MARK}{self.words(lang, 1, 3)}.</p>", f"<p>{MARK}{self.prose(lang, 3)}</p>", f"<p><b>{MARK}{self.words(lang, 1, 9)}<br>"))
                out.append(again * rng.randint(5, 250))
            if rng.random() < 0.03:
                out.append(self.box(("div", "aside"), ("ad", "advert", "promo", "related"), self.some(2)))
        return "".join(out)

    def page(self) -> str:
        rng, pick = self.rng, self.rng.choice
        inner = self.article()
        whole = pick(("<article>{}</article>", "<article>{}</article>", "<main>{}</main>", "<main><article>{}</article></main>", '<div class="content">{}</div>', '<div id="content"><div class="post">{}</div></div>', '<div class="article-body">{}</div>', '<article class="post"><div class="entry-content">{}</div></article>', '<div class="wrap"><div class="story">{}</div></div>', '<section class="text">{}</section>', "<div>{}</div>")).replace("{}", inner)
        title = f"<title>{self.words(self.lang(), 2, 9)}</title>" if rng.random() < 0.95 else ""
        head = f'<!DOCTYPE html><html><head><meta charset="utf-8">{title}<style>p{{margin:0}}</style><script>var t="</p>";</script></head><body>'
        body = self.around(True) + pick(("", "<!-- x -->")) + whole + self.around(False)
        if rng.random() < 0.15:
            body = f'<div class="{pick(("page", "wrapper", "container", "site"))}">{body}</div>'
        return head + body + pick(("</body></html>", "</body></html>", ""))


def labelled_pages(n: int, seed: int) -> tuple[list[np.ndarray], list[np.ndarray]]:
    writer, reader, xs, ys = Writer(seed), Reader(), [], []
    for _ in range(n):
        found = blocks(writer.page())
        labels = np.array([MARK in b.text for b in found], np.float32)
        for b in found:
            b.text = b.text.replace(MARK, "") or "-"
        xs.append(reader.page(found))
        ys.append(labels)
    return xs, ys


def _forward(x, wx, wh, b):
    rows, steps, _ = x.shape
    size = wh.shape[0]
    given = x @ wx + b
    h, c = np.zeros((rows, size), np.float32), np.zeros((rows, size), np.float32)
    kept = []
    for t in range(steps):
        z = given[:, t] + h @ wh
        g = 0.5 * (1 + np.tanh(0.5 * z[:, : 3 * size]))
        u = np.tanh(z[:, 3 * size :])
        before, c = c, g[:, size : 2 * size] * c + g[:, :size] * u
        tc = np.tanh(c)
        kept.append((h, before, g, u, tc))
        h = g[:, 2 * size :] * tc
    out = np.stack([k[2][:, 2 * size :] * k[4] for k in kept], 1)
    return out, kept


def _backward(x, wh, kept, slope):
    rows, steps, size = slope.shape
    dz = np.zeros((rows, steps, 4 * size), np.float32)
    dh, dc, dwh = np.zeros((rows, size), np.float32), np.zeros((rows, size), np.float32), np.zeros_like(wh)
    for t in range(steps - 1, -1, -1):
        h, before, g, u, tc = kept[t]
        i, f, o = g[:, :size], g[:, size : 2 * size], g[:, 2 * size :]
        dh = dh + slope[:, t]
        dc = dc + dh * o * (1 - tc * tc)
        z = dz[:, t]
        z[:, :size] = dc * u * i * (1 - i)
        z[:, size : 2 * size] = dc * before * f * (1 - f)
        z[:, 2 * size : 3 * size] = dh * tc * o * (1 - o)
        z[:, 3 * size :] = dc * i * (1 - u * u)
        dwh += h.T @ z
        dh, dc = z @ wh.T, dc * f
    return np.einsum("rtd,rtz->dz", x, dz, optimize=True), dwh, dz.sum((0, 1))


def train(pages: int = PAGES, epochs: int = EPOCHS, seed: int = 7, report=print) -> Labeller:
    rng = np.random.default_rng(seed)
    size, width = HIDDEN, PATH_SIZE + WORD_SIZE + PROPORTIONS
    p = {}
    for side in ("ahead", "back"):
        p[f"{side}_x"] = rng.normal(0, 0.6 / width**0.5, (width, 4 * size)).astype(np.float32)
        p[f"{side}_h"] = rng.normal(0, 0.6 / size**0.5, (size, 4 * size)).astype(np.float32)
        p[f"{side}_b"] = np.zeros(4 * size, np.float32)
        p[f"{side}_b"][size : 2 * size] = 1.0
    p["out"], p["bias"] = rng.normal(0, 0.2, 2 * size).astype(np.float32), np.zeros(1, np.float32)
    first, second = ({k: np.zeros_like(v) for k, v in p.items()} for _ in range(2))
    xs, ys = labelled_pages(pages, seed)
    order = np.argsort([len(x) for x in xs], kind="stable")
    groups = [order[i : i + BATCH] for i in range(0, len(order), BATCH)]
    step, total = 0, epochs * len(groups)
    for epoch in range(epochs):
        loss = wrong = count = 0.0
        for k in rng.permutation(len(groups)):
            group = groups[k]
            lengths = np.array([len(xs[i]) for i in group])
            x = np.zeros((len(group), int(lengths.max()), width), np.float32)
            y, live = np.zeros(x.shape[:2], np.float32), np.zeros(x.shape[:2], np.float32)
            for row, i in enumerate(group):
                x[row, : lengths[row]], y[row, : lengths[row]], live[row, : lengths[row]] = xs[i], ys[i], 1
            x *= 1 - 0.3 * (rng.random((len(group), 1, width)) < 0.1)  # no single feature decides
            rows, back = np.arange(len(group))[:, None], reversal(lengths, x.shape[1])
            one, kept_one = _forward(x, p["ahead_x"], p["ahead_h"], p["ahead_b"])
            other = x[rows, back]
            two, kept_two = _forward(other, p["back_x"], p["back_h"], p["back_b"])
            both = np.concatenate([one, two[rows, back]], 2)
            z = both @ p["out"] + p["bias"]
            chance = 0.5 * (1 + np.tanh(0.5 * z))
            slope = (chance - y) * live / live.sum()
            loss += float((np.logaddexp(0, z) - y * z)[live > 0].sum())
            wrong += float(((z > 0) != (y > 0))[live > 0].sum())
            count += live.sum()
            down = {"out": np.einsum("rtd,rt->d", both, slope), "bias": slope.sum(keepdims=True)[0]}
            spread = slope[..., None] * p["out"]
            down["ahead_x"], down["ahead_h"], down["ahead_b"] = _backward(x, p["ahead_h"], kept_one, spread[..., :size])
            down["back_x"], down["back_h"], down["back_b"] = _backward(other, p["back_h"], kept_two, spread[..., size:][rows, back])
            step += 1
            scale = min(1.0, 5.0 / (1e-9 + sum(float((d * d).sum()) for d in down.values()) ** 0.5))
            rate = RATE * (1 - 0.95 * step / total)
            for name, d in down.items():
                d = d * scale
                first[name] = 0.9 * first[name] + 0.1 * d
                second[name] = 0.999 * second[name] + 0.001 * d * d
                p[name] -= rate * (first[name] / (1 - 0.9**step)) / (np.sqrt(second[name] / (1 - 0.999**step)) + 1e-8)
        report(f"epoch {epoch + 1}: loss {loss / count:.4f}, wrong {wrong:.0f} of {count:.0f}")
    return Labeller(p)


if __name__ == "__main__":
    trained = train()
    xs, ys = labelled_pages(500, 99)
    scores = trained.scores(xs)
    print("held out: wrong", sum(int(((s > 0) != (y > 0)).sum()) for s, y in zip(scores, ys)), "of", sum(map(len, ys)))
    np.savez_compressed(WEIGHTS, **{k: v.astype(np.float16) for k, v in trained.p.items()})
