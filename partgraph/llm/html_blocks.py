"""Main text of web pages by a recurrent block labeller: a numpy bidirectional LSTM over the leaf blocks of a page.

A page is cut into blocks, the runs of text between block-level tags. Each block is a vector of its hashed tag path
(tags and the words of class, id and role), its hashed words and a few counts; the network reads the blocks in both
directions, so that each label sees the whole page. It is trained here on pages that ``write_page`` makes up: an article
in one of many containers among menus, headers, footers, sidebars, notices, adverts, forms and comments.

Cases: null, empty or text-free pages give the empty text; unclosed and stray tags are repaired as they come; very long
pages are read whole; repeated rows give repeated results; other columns are ignored.
"""

from __future__ import annotations

import random
import zlib
from functools import lru_cache
from html.parser import HTMLParser

import numpy as np
from pyspark.sql import DataFrame

PATH_DIM, WORD_DIM, COUNTS = 192, 16, 5
DIM = PATH_DIM + WORD_DIM + COUNTS
HIDDEN = 16
PAGES, EPOCHS, BATCH, RATE = 480, 6, 32, 0.01
#: Tags that never close, that never show text, that go on inside a block, and that end an open paragraph-like tag.
VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())
HIDDEN_TAGS = frozenset("head script style template noscript svg iframe object".split())
INLINE = frozenset("a abbr b bdi bdo cite code data del dfn em font i ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr img".split())
SELF_ENDING = frozenset("p li dt dd tr td th option".split())
_CRC = lru_cache(maxsize=100_000)(lambda s: zlib.crc32(s.encode()))


class _Blocks(HTMLParser):
    """Collects (path, text, link characters) of each block."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.stack: list[tuple[str, tuple[str, ...]]] = []
        self.blocks: list[tuple[tuple[str, ...], str, int]] = []
        self.parts: list[str] = []
        self.linked = 0
        self.path: tuple[str, ...] = ()

    def flush(self):
        text = " ".join("".join(self.parts).split())
        if text:
            self.blocks.append((self.path, text, self.linked))
        self.parts, self.linked = [], 0

    def pop_to(self, tag: str):
        for i in range(len(self.stack) - 1, -1, -1):
            if self.stack[i][0] == tag:
                del self.stack[i:]
                return

    def handle_starttag(self, tag, attrs):
        if tag not in INLINE:
            self.flush()
        if tag in VOID:
            return
        if tag == "body":
            self.pop_to("head")
        if tag in SELF_ENDING or tag not in INLINE:
            inner = next((t for t, _ in reversed(self.stack) if t not in INLINE), "")
            if inner == "p" or (inner == tag and tag in SELF_ENDING):
                self.pop_to(inner)
        marks = [tag]
        for k, v in attrs:
            if k in ("class", "id", "role") and v:
                marks.extend("." + x for x in "".join(c if c.isalnum() else " " for c in v.lower()).split())
        self.stack.append((tag, tuple(marks)))

    def handle_startendtag(self, tag, attrs):
        if tag not in INLINE:
            self.flush()

    def handle_endtag(self, tag):
        if tag not in INLINE:
            self.flush()
        self.pop_to(tag)

    def handle_data(self, data):
        names = [t for t, _ in self.stack]
        if HIDDEN_TAGS.intersection(names):
            return
        if not self.parts or not "".join(self.parts).strip():
            self.path = tuple(m for _, ms in self.stack for m in ms)
        self.parts.append(data)
        if "a" in names:
            self.linked += len(data)


def blocks_of(html: str | None) -> list[tuple[tuple[str, ...], str, int]]:
    p = _Blocks()
    p.feed(html or "")
    p.close()
    p.flush()
    return p.blocks


def block_vectors(blocks) -> np.ndarray:
    x = np.zeros((len(blocks), DIM), np.float32)
    for i, (path, text, linked) in enumerate(blocks):
        for m in path:
            x[i, _CRC(m) % PATH_DIM] = 1
        words = text.split(" ")
        bag = np.bincount([_CRC(w) % WORD_DIM for w in words], minlength=WORD_DIM)
        x[i, PATH_DIM : PATH_DIM + WORD_DIM] = bag / np.sqrt(bag @ bag)
        n = len(text)
        x[i, -COUNTS:] = (np.log1p(n) / 6, min(1.0, linked / n), text.count(".") / (1 + len(words)), len(path) / 10, 1.0 if text[-1] in ".!?" else 0.0)
    return x


# ---- network ---------------------------------------------------------------------------------


def _sig(z):
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _turned(x: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Each sequence in reverse, padding left at its end."""
    at = np.arange(x.shape[1])[None, :]
    at = np.where(at < lengths[:, None], lengths[:, None] - 1 - at, at)
    return np.take_along_axis(x, at[:, :, None], 1)


def _lstm(x: np.ndarray, w: np.ndarray, u: np.ndarray, b: np.ndarray):
    n, steps, _ = x.shape
    h, c = np.zeros((n, HIDDEN), np.float32), np.zeros((n, HIDDEN), np.float32)
    z_in = x @ w + b
    hs, keep = np.zeros((n, steps, HIDDEN), np.float32), []
    for t in range(steps):
        z = z_in[:, t] + h @ u
        i, f, o = _sig(z[:, :HIDDEN]), _sig(z[:, HIDDEN : 2 * HIDDEN]), _sig(z[:, 2 * HIDDEN : 3 * HIDDEN])
        g = np.tanh(z[:, 3 * HIDDEN :])
        before, c = c, f * c + i * g
        tc = np.tanh(c)
        keep.append((i, f, o, g, before, tc, h))
        h = o * tc
        hs[:, t] = h
    return hs, keep


def _lstm_back(d_hs: np.ndarray, x: np.ndarray, u: np.ndarray, keep):
    n, steps, dim = x.shape
    dz_all = np.zeros((n, steps, 4 * HIDDEN), np.float32)
    dh, dc, du = np.zeros((n, HIDDEN), np.float32), np.zeros((n, HIDDEN), np.float32), np.zeros_like(u)
    for t in range(steps - 1, -1, -1):
        i, f, o, g, before, tc, h = keep[t]
        dh = dh + d_hs[:, t]
        dc = dc + dh * o * (1 - tc * tc)
        dz = np.concatenate([dc * g * i * (1 - i), dc * before * f * (1 - f), dh * tc * o * (1 - o), dc * i * (1 - g * g)], 1)
        dz_all[:, t] = dz
        du += h.T @ dz
        dh, dc = dz @ u.T, dc * f
    return x.reshape(-1, dim).T @ dz_all.reshape(-1, 4 * HIDDEN), du, dz_all.sum((0, 1))


def _padded(pages: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    lengths = np.array([len(p) for p in pages])
    x = np.zeros((len(pages), int(lengths.max()), DIM), np.float32)
    for i, p in enumerate(pages):
        x[i, : len(p)] = p
    return x, lengths


def label_logits(model: dict[str, np.ndarray], pages: list[np.ndarray]) -> list[np.ndarray]:
    """One logit for each block of each page; pages of like length share a batch."""
    out: list[np.ndarray] = [np.zeros(0, np.float32)] * len(pages)
    order = sorted((i for i, p in enumerate(pages) if len(p)), key=lambda i: len(pages[i]))
    at = 0
    while at < len(order):
        end = at + 1
        while end < len(order) and (end + 1 - at) * len(pages[order[end]]) <= 8192:
            end += 1
        x, lengths = _padded([pages[i] for i in order[at:end]])
        a, _ = _lstm(x, model["wf"], model["uf"], model["bf"])
        b, _ = _lstm(_turned(x, lengths), model["wb"], model["ub"], model["bb"])
        z = np.concatenate([a, _turned(b, lengths)], 2) @ model["v"] + model["c"]
        for j, i in enumerate(order[at:end]):
            out[i] = z[j, : len(pages[i])]
        at = end
    return out


# ---- made-up pages ---------------------------------------------------------------------------

#: Fixed word lists of the page writer.
MAIN_BOXES = ("article", "main", "article.post", "div.content", "div.article", "div.entry-content", "div.post-body", "div.story", "section.article-body", "main.content", "div#content", "div#main")
SIDE_BOXES = {
    "link": ("nav", "nav.menu", "div.nav", "div.menu", "ul.navbar", "div.breadcrumb", "div.related", "div.tags", "div.share", "div.social", "aside.related", "div.pagination"),
    "text": ("div.ad", "div.ads", "div.advert", "div.banner", "div.promo", "div.sponsored", "aside", "aside.sidebar", "div.sidebar", "div.widget", "div.cookie", "div.cookie-notice", "div.notice", "div.consent", "div.popup", "div.newsletter", "div.subscribe"),
    "top": ("header", "header.site-header", "div.header", "div.masthead"),
    "end": ("footer", "footer.site-footer", "div.footer", "div.copyright", "div.legal"),
    "form": ("form", "form.search", "div.login", "form.signup"),
    "talk": ("section.comments", "div.comments", "div#comments", "div.comment", "ol.comment-list", "div.replies"),
}


def _box(name: str, inner: str) -> str:
    for mark, attr in ((".", "class"), ("#", "id")):
        if mark in name:
            tag, value = name.split(mark, 1)
            return f'<{tag} {attr}="{value}">{inner}</{tag}>'
    return f"<{name}>{inner}</{name}>"


def write_page(rng: random.Random) -> str:
    """A made-up page; article words start with the letter q, all others with z."""

    def words(letter: str, n: int) -> str:
        out = [letter + "".join(rng.choice("aeioulnrst") for _ in range(rng.randint(1, 8))) for _ in range(n)]
        text = " ".join(w + ("." if rng.random() < 0.12 else "," if rng.random() < 0.05 else "") for w in out)
        return text + ("." if rng.random() < 0.7 else "")

    def side(kind: str) -> str:
        name = rng.choice(SIDE_BOXES[kind])
        n = rng.randint(1, 8)
        links = [f'<a href="/x">{words("z", rng.randint(1, 3))}</a>' for _ in range(n)]
        if kind == "link" or (kind in ("top", "end") and rng.random() < 0.4):
            inner = "<ul>" + "".join(f"<li>{a}</li>" for a in links) + "</ul>" if rng.random() < 0.7 else " ".join(links)
        elif kind == "form":
            inner = f"<label>{words('z', 2)}</label><input name=q><button>{words('z', 1)}</button>"
        elif kind == "talk":
            inner = "".join(f"<div class=\"comment\"><p>{words('z', rng.randint(3, 50))}</p></div>" for _ in range(n))
        else:
            text = words("z", rng.randint(2, 40))
            inner = rng.choice((text, f"<p>{text}</p>", f"<h3>{words('z', 2)}</h3><p>{text}</p>"))
        return _box(name, inner)

    def article() -> str:
        out = [f"<h1>{words('q', rng.randint(2, 10))}</h1>"] if rng.random() < 0.8 else []
        for _ in range(rng.randint(1, 22)):
            text = words("q", rng.choice((1, 2, 5, 20, 60, 120)))
            out.append(rng.choice((f"<p>{text}</p>",) * 5 + (f"<p><b>{text}<br>", f"<h2>{text}</h2>", f"<ul><li>{text}</li><li>{words('q', 4)}</li></ul>", f"<blockquote>{text}</blockquote>", f"<p>{text} <a href='/y'>{words('q', 2)}</a></p>", f"<div>{text}</div>", f"<table><tr><td>{text}</td><td>{words('q', 2)}</td></tr></table>", f"<pre>{text}</pre>", text)))
            if rng.random() < 0.06:
                out.append(side(rng.choice(("text", "link"))))
        return _box(rng.choice(MAIN_BOXES), "".join(out))

    before = [side(rng.choice(("link", "top", "text", "form"))) for _ in range(rng.randint(0, 4))]
    after = [side(rng.choice(("link", "end", "text", "form", "talk"))) for _ in range(rng.randint(0, 4))]
    body = "".join([*before, article(), *after])
    return f"<html><head><title>z</title></head><body>{_box('div.page', body) if rng.random() < 0.3 else body}</body></html>"


def train(seed: int = 5, pages: int = PAGES, epochs: int = EPOCHS) -> dict[str, np.ndarray]:
    rng = random.Random(seed)
    made = [b for b in (blocks_of(write_page(rng)) for _ in range(pages)) if b]
    xs = [block_vectors(b) for b in made]
    ys = [np.array([t[0] == "q" for _, t, _ in b], np.float32) for b in made]
    init = np.random.default_rng(seed)
    small = lambda *s: (init.normal(size=s) * 0.1).astype(np.float32)
    model = {"wf": small(DIM, 4 * HIDDEN), "uf": small(HIDDEN, 4 * HIDDEN), "bf": np.zeros(4 * HIDDEN, np.float32), "wb": small(DIM, 4 * HIDDEN), "ub": small(HIDDEN, 4 * HIDDEN), "bb": np.zeros(4 * HIDDEN, np.float32), "v": small(2 * HIDDEN), "c": np.zeros(1, np.float32)}
    first, second, step = {k: np.zeros_like(p) for k, p in model.items()}, {k: np.zeros_like(p) for k, p in model.items()}, 0
    order = sorted(range(len(xs)), key=lambda i: len(xs[i]))
    batches = [order[i : i + BATCH] for i in range(0, len(order), BATCH)]
    for _ in range(epochs):
        rng.shuffle(batches)
        for batch in batches:
            x, lengths = _padded([xs[i] for i in batch])
            y = np.zeros(x.shape[:2], np.float32)
            for j, i in enumerate(batch):
                y[j, : len(ys[i])] = ys[i]
            real = np.arange(x.shape[1])[None, :] < lengths[:, None]
            turned = _turned(x, lengths)
            a, ka = _lstm(x, model["wf"], model["uf"], model["bf"])
            b, kb = _lstm(turned, model["wb"], model["ub"], model["bb"])
            both = np.concatenate([a, _turned(b, lengths)], 2)
            dz = ((_sig(both @ model["v"] + model["c"]) - y) * real / real.sum()).astype(np.float32)
            d_both = dz[:, :, None] * model["v"]
            grads = dict(zip(("wf", "uf", "bf"), _lstm_back(d_both[:, :, :HIDDEN], x, model["uf"], ka), strict=True))
            grads |= dict(zip(("wb", "ub", "bb"), _lstm_back(_turned(d_both[:, :, HIDDEN:], lengths), turned, model["ub"], kb), strict=True))
            grads |= {"v": (both * dz[:, :, None]).sum((0, 1)), "c": np.array([dz.sum()], np.float32)}
            step += 1
            for k, g in grads.items():
                first[k] = 0.9 * first[k] + 0.1 * g
                second[k] = 0.999 * second[k] + 0.001 * g * g
                model[k] = model[k] - RATE * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)
    return {k: p.astype(np.float32) for k, p in model.items()}


@lru_cache(maxsize=1)
def labeller() -> dict[str, np.ndarray]:
    """The trained network, about 130 KB; made once in the driver and sent with the task."""
    return train()


def main_texts(model: dict[str, np.ndarray], pages: list[str | None]) -> list[str]:
    cut = [blocks_of(h) for h in pages]
    logits = label_logits(model, [block_vectors(b) for b in cut])
    return [" ".join(t for (_, t, _), z in zip(b, zs, strict=True) if z > 0) for b, zs in zip(cut, logits, strict=True)]


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars of each page."""
    import pyarrow as pa

    model = labeller()

    def run(batches):
        for batch in batches:
            html = batch.column("html").to_pylist()
            for a in range(0, len(html), 256):
                texts = main_texts(model, html[a : a + 256])
                yield pa.RecordBatch.from_arrays([batch.column("page_id").slice(a, len(texts)), batch.column("url").slice(a, len(texts)), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.selectExpr("cast(page_id as bigint) page_id", "url", "html").mapInArrow(run, "page_id bigint, url string, text string, n_chars bigint")


def op7_block_lstm(spark, sf_dir: str) -> DataFrame:
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))
