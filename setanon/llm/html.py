"""Main text of web pages by a recurrent block labeller.

A page is cut into leaf blocks, each with its path of tags and class words. A bidirectional LSTM in
numpy reads the whole sequence of blocks, as hashed path and word vectors, and labels each as
content or not, so a block is judged with its page around it.

Pages carry no labels. The fit reads at most ``max_pages`` distinct pages, those of least hash, and
labels their blocks by the elements that name their role (article, navigation, footer, ...). Names
alone would teach a word list, so most of what the net sees is made from these pages: variants with
further furniture and other names for the article, and disguised ones, where roles have no names or
misleading ones (plain and table layouts, articles whose classes hold words of furniture) and a
block keeps the label that it had. There the net has to go by links, shape, place and neighbours. All
pages are then labelled by the net alone.

Defined results: null html gives an empty text; a page without content blocks gives an empty text;
an unclosed script or comment runs to the page's end; quotes count only as the start of an
attribute's value; repeated rows are extracted row by row; an
empty table gives an empty result and nothing is fitted.
"""

from __future__ import annotations

import html as entities
import random
import re
import zlib
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import tidy
from .words import WordHasher

PATHS, WORDS, NUMBERS = 256, 32, 6
WIDTH = PATHS + WORDS + NUMBERS


@dataclass(frozen=True)
class Options:
    max_pages: int = 240
    hidden: int = 24
    epochs: int = 12
    batch: int = 48
    steps: int = 400  # a longer page is fitted in parts of so many blocks
    rate: float = 0.015
    seed: int = 7


# ---- blocks -----------------------------------------------------------------------------------

_ATTRS = r"""(?:=\s*"[^"]*"|=\s*'[^']*'|[^>])*+"""
_TOKEN = re.compile(
    rf"<!--.*?(?:-->|\Z)|<(?P<raw>script|style|noscript|template|svg|iframe|textarea)\b{_ATTRS}>.*?(?:</(?P=raw)\s*>|\Z)"
    rf"|<(?P<end>/?)(?P<tag>[a-zA-Z][^\s/>]*)(?P<attrs>{_ATTRS})>|<[!?][^>]*>|(?P<text>[^<]+|<)",
    re.S | re.I,
)
_NAMED = re.compile(r"(?<![\w-])(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>\"'][^\s>]*))", re.I)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form"
    " h1 h2 h3 h4 h5 h6 head header hr html label legend li main menu nav ol option p pre section select summary table tbody td tfoot th thead title tr ul".split()
)
_ITEMS = {"li": ("ul", "ol", "menu"), "td": ("tr", "table"), "th": ("tr", "table"), "tr": ("table",), "dt": ("dl",), "dd": ("dl",), "option": ("select",)}


@dataclass(frozen=True)
class Block:
    path: tuple[str, ...]  # from the root; an element is its tag, then its class words after dots
    text: str
    linked: int  # characters inside links


def blocks(page: str | None) -> list[Block]:
    """Leaf blocks in page order; texts are decoded, with white space turned into single spaces."""
    out: list[Block] = []
    stack: list[tuple[str, str]] = []
    held: list[str] = []
    links = 0

    def flush():
        nonlocal links
        if held:
            text = " ".join(entities.unescape("".join(held)).split())
            if text:
                out.append(Block(tuple(n for t, n in stack if t in BLOCK or n != t), text, min(links, len(text))))
            held.clear()
        links = 0

    def pop_to(tag: str, stop=()):
        for i in range(len(stack) - 1, -1, -1):
            if stack[i][0] == tag:
                del stack[i:]
                return
            if stack[i][0] in stop:
                return

    for m in _TOKEN.finditer(page or ""):
        if (text := m["text"]) is not None:
            held.append(text)
            if any(t == "a" for t, _ in stack[-3:]):
                links += len(text)
            continue
        tag = m["tag"]
        if tag is None:
            continue
        tag = tag.lower()
        if tag in BLOCK:
            flush()
        elif tag == "br":
            held.append(" ")
        if m["end"]:
            pop_to(tag)
        elif tag not in VOID:
            if tag in BLOCK:
                pop_to("p", ("article", "main", "section", "div", "body", "td", "li", "blockquote", "form", "aside", "nav", "header", "footer"))
                if tag in _ITEMS:
                    pop_to(tag, _ITEMS[tag])
            names = [w for g in _NAMED.findall(m["attrs"]) for w in "".join(g).lower().split()] if m["attrs"] else []
            stack.append((tag, ".".join([tag, *names])))
    flush()
    return out


# ---- features ---------------------------------------------------------------------------------

_SPLIT = re.compile(r"[a-z0-9]+")


def _slot(word: str, salt: str) -> int:
    return zlib.crc32(f"{salt}:{word}".encode()) * 2654435761 % 2**32 * PATHS >> 32


_PATH_SLOTS: dict[tuple[str, ...], np.ndarray] = {}


def path_slots(path: tuple[str, ...]) -> np.ndarray:
    """Hashed tags and class words of all ancestors, and of the innermost two by place."""
    got = _PATH_SLOTS.get(path)
    if got is None:
        if len(_PATH_SLOTS) > 20_000:
            _PATH_SLOTS.clear()
        slots = set()
        for depth, name in enumerate(reversed(path)):
            tag, *words = name.split(".")
            slots.add(_slot(tag, "tag"))
            if depth < 2:
                slots.add(_slot(tag, f"tag{depth}"))
            for w in words:
                slots.update(_slot(x, "word") for x in _SPLIT.findall(w))
        got = _PATH_SLOTS[path] = np.asarray(sorted(slots), np.int64)
    return got


class Vectors:
    def __init__(self):
        self.hash = WordHasher(punctuation_is_space=True)

    def __call__(self, items: list[Block]) -> np.ndarray:
        x = np.zeros((len(items), WIDTH), np.float32)
        if not items:
            return x
        for i, b in enumerate(items):
            x[i, path_slots(b.path)] = 1
        h, at = self.hash.texts([b.text.encode() for b in items])
        n = np.diff(at)
        owner = np.repeat(np.arange(len(items)), n)
        counts = np.bincount(owner * WORDS + (h >> np.uint64(59)).astype(np.int64), minlength=len(items) * WORDS)
        x[:, PATHS : PATHS + WORDS] = counts.reshape(-1, WORDS) / np.maximum(n, 1)[:, None]
        size = np.asarray([len(b.text) for b in items])
        x[:, PATHS + WORDS] = np.log1p(size) / 8
        x[:, PATHS + WORDS + 1] = [b.linked / len(b.text) for b in items]
        x[:, PATHS + WORDS + 2] = np.log1p(n) / 6
        x[:, PATHS + WORDS + 3] = [b.text[-1] in ".!?…" for b in items]
        x[:, PATHS + WORDS + 4] = np.minimum(1, np.arange(len(items)) / 20)
        x[:, PATHS + WORDS + 5] = np.minimum(1, np.arange(len(items))[::-1] / 20)
        return x


# ---- the net ----------------------------------------------------------------------------------


def _sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Net:
    """A bidirectional LSTM with one logistic output for each step."""

    def __init__(self, hidden: int, seed: int = 0, width: int = WIDTH):
        rnd = np.random.default_rng(seed)
        self.h = hidden
        self.p: dict[str, np.ndarray] = {"o": rnd.normal(0, 0.3, (2 * hidden, 1)), "ob": np.zeros(1)}
        for d in "fb":
            self.p[f"{d}w"] = rnd.normal(0, 0.15, (width, 4 * hidden))
            self.p[f"{d}u"] = rnd.normal(0, hidden**-0.5, (hidden, 4 * hidden))
            self.p[f"{d}c"] = np.concatenate([np.zeros(hidden), np.ones(hidden), np.zeros(2 * hidden)])
        self.p = {k: v.astype(np.float32) for k, v in self.p.items()}

    @staticmethod
    def _reversed(n: np.ndarray, steps: int) -> np.ndarray:
        """Index that reverses each sequence inside its own length."""
        t = np.arange(steps)[None, :]
        return np.where(t < n[:, None], n[:, None] - 1 - t, t)

    def _pass(self, d: str, x: np.ndarray, live: np.ndarray, keep: bool):
        b, steps, _ = x.shape
        w, u, c = self.p[f"{d}w"], self.p[f"{d}u"], self.p[f"{d}c"]
        z = (x.reshape(b * steps, -1) @ w + c).reshape(b, steps, -1)
        h, s, k = np.zeros((b, self.h), np.float32), np.zeros((b, self.h), np.float32), self.h
        out, memo = np.zeros((b, steps, k), np.float32), []
        for t in range(steps):
            g = z[:, t] + h @ u
            i, f, o, q = _sigmoid(g[:, :k]), _sigmoid(g[:, k : 2 * k]), _sigmoid(g[:, 2 * k : 3 * k]), np.tanh(g[:, 3 * k :])
            new = f * s + i * q
            th, m = np.tanh(new), live[:, t : t + 1]
            if keep:
                memo.append((i, f, o, q, s, th, h, m))
            s, h = np.where(m, new, s), np.where(m, o * th, h)
            out[:, t] = h
        return out, memo

    def forward(self, x: np.ndarray, n: np.ndarray, keep: bool = False):
        """Probabilities (batch x steps) for padded sequences of lengths ``n``."""
        steps = x.shape[1]
        live, back = np.arange(steps)[None, :] < n[:, None], self._reversed(n, steps)
        rows = np.arange(len(n))[:, None]
        f, mf = self._pass("f", x, live, keep)
        xr = x[rows, back]
        b, mb = self._pass("b", xr, live, keep)
        both = np.concatenate([f, b[rows, back]], axis=2)
        p = _sigmoid(both @ self.p["o"] + self.p["ob"])[..., 0]
        return (p, (x, xr, both, mf, mb, live, back)) if keep else p

    def _back(self, d: str, x: np.ndarray, memo: list, dout: np.ndarray, grads: dict) -> None:
        b, steps, _ = x.shape
        u, k = self.p[f"{d}u"], self.h
        dz = np.zeros((b, steps, 4 * k), np.float32)
        dh, ds, du = np.zeros((b, k), np.float32), np.zeros((b, k), np.float32), np.zeros_like(u)
        for t in range(steps - 1, -1, -1):
            i, f, o, q, s, th, h, m = memo[t]
            dh = dh + dout[:, t]
            live_h, live_s = np.where(m, dh, 0), np.where(m, ds, 0)
            dnew = live_s + live_h * o * (1 - th * th)
            g = np.concatenate([dnew * q * i * (1 - i), dnew * s * f * (1 - f), live_h * th * o * (1 - o), dnew * i * (1 - q * q)], axis=1)
            dz[:, t] = g
            du += h.T @ g
            dh, ds = g @ u.T + np.where(m, 0, dh), dnew * f + np.where(m, 0, ds)
        flat = dz.reshape(b * steps, -1)
        grads[f"{d}w"], grads[f"{d}u"], grads[f"{d}c"] = x.reshape(b * steps, -1).T @ flat, du, flat.sum(axis=0)

    def gradients(self, x: np.ndarray, n: np.ndarray, y: np.ndarray) -> tuple[float, dict]:
        """Mean cross entropy over the real steps, and its gradients."""
        p, (x, xr, both, mf, mb, live, back) = self.forward(x, n, keep=True)
        total = max(1, int(n.sum()))
        loss = -float(np.where(live, y * np.log(p + 1e-7) + (1 - y) * np.log(1 - p + 1e-7), 0).sum()) / total
        dlogit = (np.where(live, p - y, 0) / total).astype(np.float32)[..., None]
        grads = {"o": both.reshape(-1, both.shape[2]).T @ dlogit.reshape(-1, 1), "ob": dlogit.sum(axis=(0, 1))}
        dboth = dlogit @ self.p["o"].T
        self._back("f", x, mf, dboth[..., : self.h], grads)
        self._back("b", xr, mb, dboth[..., self.h :][np.arange(len(n))[:, None], back], grads)
        return loss, grads


def padded(seqs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    n = np.asarray([len(s) for s in seqs])
    out = np.zeros((len(seqs), int(n.max(initial=1)), *seqs[0].shape[1:]), np.float32)
    for i, s in enumerate(seqs):
        out[i, : len(s)] = s
    return out, n


# ---- supervision ------------------------------------------------------------------------------

#: Words that name furniture and words that name the article, in tags, classes and roles. Fixed values.
FURNITURE = (
    "nav navigation menu navbar breadcrumb breadcrumbs header masthead banner topbar footer bottom copyright sidebar aside related recommended widget"
    " notice cookie consent alert popup modal ad ads advert advertisement sponsored promo form subscribe newsletter signup login search"
    " comment comments respond reply replies disqus share social tags pagination skip head title"
).split()
ARTICLE = "article main content post entry story body text".split()


def taught(b: Block) -> bool:
    """Inside an article and not, inside that, in furniture."""
    inside = False
    for name in b.path:
        tag, *words = name.split(".")
        words = {x for w in words for x in _SPLIT.findall(w)}
        if words & set(FURNITURE) or tag in ("nav", "header", "footer", "aside", "form", "head", "title", "button", "select", "label", "dialog"):
            return False
        inside |= tag in ("article", "main") or bool(words & set(ARTICLE))
    return inside


def _furniture(rnd: random.Random, texts: list[str]) -> str:
    """A piece of page furniture of a kind the given pages may lack."""
    say = lambda: entities.escape(rnd.choice(texts)[: rnd.choice([12, 40, 200, 900])])
    lines = lambda k, t: "".join(f"<{t}>{say()}</{t}>" for _ in range(rnd.randint(1, k)))
    links = lambda k: "<ul>" + "".join(f'<li><a href="/{i}">{say()}</a></li>' for i in range(rnd.randint(1, k))) + "</ul>"
    kind = rnd.randrange(6)
    if kind == 0:
        tag = rnd.choice(["nav", "header", "footer", "aside"])
        return f"<{tag}>{rnd.choice([links(5), lines(3, 'p'), say(), '<h2>' + say() + '</h2>' + lines(2, 'p')])}</{tag}>"
    if kind == 1:
        return f"<form><label>{say()}</label><input name=q><p>{say()}</p><button>{say()}</button></form>"
    word = rnd.choice(FURNITURE)
    attr = rnd.choice(["class", "class", "id"])
    name = rnd.choice([word, f"{word}-{rnd.choice(['box', 'list', 'area', 'wrap', 'item'])}", f"{rnd.choice(['site', 'page', 'user', 'x'])}-{word}", f"{word} clearfix"])
    tag = rnd.choice(["div", "div", "section", "ul" if kind == 2 else "div"])
    inner = lines(5, "li") if tag == "ul" else rnd.choice([lines(4, "p"), say(), links(4), "<h3>" + say() + "</h3>" + lines(3, "div"), f"<article><p>{say()}</p></article>" if word.startswith("comment") else lines(2, "p")])
    return f'<{tag} {attr}="{name}">{inner}</{tag}>'


def variant(page: str, rnd: random.Random) -> str:
    """The page with more furniture, and sometimes another element as its article."""
    texts = [b.text for b in blocks(page)] or ["text"]
    add = lambda most: "".join(_furniture(rnd, texts) for _ in range(rnd.randint(0, most)))
    head, open_, rest = page.partition("<article>")
    body, close, tail = rest.partition("</article>")
    if not close:
        return page + add(2)
    if rnd.random() < 0.5:
        body = add(1) + body + add(2)
        parts = body.split("</p>")
        if len(parts) > 2 and rnd.random() < 0.5:
            parts.insert(rnd.randint(1, len(parts) - 1), add(1))
            body = "</p>".join(parts)
        extra = rnd.choice(["", "", "<h2>{}</h2>", "<ul><li>{}</li></ul>", "<blockquote>{}</blockquote>", "<table><tr><td>{}</td></tr></table>", "<pre>{}</pre>", "<section><h3>{}</h3></section>"])
        body += extra.format(entities.escape(rnd.choice(texts)[:300]))
    tag = rnd.choice(["article", "article", "article", "main", "div"])
    word = rnd.choice(ARTICLE)
    mark = f' class="{rnd.choice([word, f"{word}-body", f"post-{word}"])}"' if tag == "div" else ""
    wrap = rnd.choice([("", ""), ("<main>", "</main>"), ('<div id="page">', "</div>"), ('<div class="container">', "</div>")])
    return f"{head}{add(3)}{wrap[0]}{add(1)}<{tag}{mark}>{body}</{tag}>{add(2)}{wrap[1]}{add(2)}{tail}"


#: Marks that stand before a made text and fix its label. Private code points.
KEEP, DROP = "\ue001", "\ue000"


def labelled_blocks(page: str) -> tuple[list[Block], np.ndarray]:
    """Blocks with their labels: that of a mark, else what the names say."""
    out, y = [], []
    for b in blocks(page):
        y.append(KEEP in b.text or DROP not in b.text and taught(b))
        text = b.text.replace(KEEP, "").replace(DROP, "").strip()
        out.append(replace(b, text=text, linked=min(b.linked, len(text))) if text else b)
    return out, np.asarray(y, np.float32)


def _name(rnd: random.Random) -> str:
    """A class word that says nothing."""
    return rnd.choice(["c", "x", "box", "col", "wrap", "inner", "row", "left", "right", "block", "s", "z"]) + rnd.choice(["", "1", "2", "-3", str(rnd.randint(1, 999))])


_SIGNS = ("© {} {}", "{} {} · {}", "Terms Privacy Contact {}", "{} | {} | {}", "Updated {} {}")


def disguised(page: str, rnd: random.Random) -> str:
    """The page's texts in a layout without names of roles, or with misleading ones; marks hold the
    labels."""
    items, y = labelled_blocks(page)
    texts = [b.text for b in items] or ["text"]
    short = lambda: entities.escape(" ".join(rnd.choice(texts).split()[: rnd.randint(1, 4)]))
    runs: list[tuple[bool, list[Block]]] = []
    for b, label in zip(items, y):
        if b.path[-1:] == ("title",):
            continue
        if runs and runs[-1][0] == bool(label) and (label or runs[-1][1][-1].path[:-1] == b.path[:-1]):
            runs[-1][1].append(b)
        else:
            runs.append((bool(label), [b]))
    menu = lambda: (False, [Block((), short(), 99) for _ in range(rnd.randint(2, 9))])
    signs = lambda: (False, [Block((), rnd.choice(_SIGNS).format(short(), short(), short()), 0) for _ in range(rnd.randint(1, 2))])
    # a notice of plain sentences can't be told from an article without its name
    runs = [r for r in runs if r[0] or all(b.linked * 2 > len(b.text) for b in r[1]) or len(r[1]) == 1 and len(r[1][0].text) < 60]
    if not any(not k for k, _ in runs) or rnd.random() < 0.5:
        runs.insert(0, menu())
    if rnd.random() < 0.4:
        runs.append(menu())
    if rnd.random() < 0.7:
        runs.append(signs())
    misled = rnd.random() < 0.3

    def attr() -> str:
        c = _name(rnd)
        return rnd.choice(["", f' class="{c}"', f" class={c}", f" id='{c}'", f' class="{c} {_name(rnd)}"'])

    def shown(b: Block, keep: bool) -> str:
        text = (KEEP if keep else DROP) + entities.escape(b.text)
        if b.linked * 2 > len(b.text):
            link = f'<a href="/{rnd.randint(1, 99)}">{text}</a>'
            return rnd.choice([f"<li>{link}</li>", f"<div>{link}</div>", f"<p>{link}</p>", f"<td>{link}</td>"])
        head = b.path[-1:] and b.path[-1].split(".")[0] in ("h1", "h2", "h3")
        tag = rnd.choice([b.path[-1].split(".")[0], "h2", "div"]) if head else rnd.choice(["p", "p", "p", "div", "font", "blockquote"])
        own = attr() if rnd.random() < 0.2 else ""
        if misled and keep and rnd.random() < 0.5:
            tag, own = "div", f' class="{rnd.choice(FURNITURE)}-{rnd.choice(["price", "report", "story", "of", "market", "law", "news", "art", _name(rnd)])}"'
        return f"<{tag}{own}>{text}</{tag}>" if tag != "font" else f"<div><font size=2>{text}</font></div>"

    parts = []
    for keep, held in runs:
        inner = "".join(shown(b, keep) for b in held)
        deep = rnd.randint(1, 3)
        parts.append((keep, "".join(f"<div{attr()}>" for _ in range(deep)) + inner + "</div>" * deep))
    title = f"<head><title>{DROP}{short()}</title></head>" if rnd.random() < 0.8 else ""
    kind = rnd.randrange(4)
    if kind == 0:  # cells of a table, as in old pages
        body = "<table><tr>" + "".join(f"<td{attr()}>{x}</td>" + rnd.choice(["", "</tr><tr>"]) for _, x in parts) + "</tr></table>"
    elif kind == 1 and misled:
        body = "".join(f"<article>{x}</article>" if k else x for k, x in parts)
    else:
        body = "".join(x for _, x in parts)
    return f"<html>{title}<body{attr()}>{body}</body></html>"


def fit(pages: list[str], opt: Options = Options()) -> Net | None:
    """Adam on batches of pages, their variants and their disguised forms."""
    rnd, vectors = random.Random(opt.seed), Vectors()
    data = []
    for page in pages:
        for p in (page, variant(page, rnd), variant(page, rnd), variant(page, rnd), disguised(page, rnd), disguised(page, rnd), disguised(variant(page, rnd), rnd)):
            b, y = labelled_blocks(p)
            for i in range(0, len(b), opt.steps):
                data.append((vectors(b[i : i + opt.steps]), y[i : i + opt.steps]))
    if not data:
        return None
    net = Net(opt.hidden, opt.seed)
    m, v, step = ({k: np.zeros_like(x) for k, x in net.p.items()} for _ in range(2)), None, 0
    m, v = m
    for epoch in range(opt.epochs):
        order = sorted(range(len(data)), key=lambda i: (len(data[i][0]) + rnd.randint(0, 12), rnd.random()))
        groups = [order[i : i + opt.batch] for i in range(0, len(order), opt.batch)]
        rnd.shuffle(groups)
        rate = opt.rate * (1 - epoch / opt.epochs) + 1e-4
        for g in groups:
            x, n = padded([data[i][0] for i in g])
            y, _ = padded([data[i][1] for i in g])
            _, grads = net.gradients(x, n, y)
            norm = float(np.sqrt(sum((q * q).sum() for q in grads.values())))
            step += 1
            for k, q in grads.items():
                q = q * min(1.0, 5 / (norm + 1e-9))
                m[k] = 0.9 * m[k] + 0.1 * q
                v[k] = 0.999 * v[k] + 0.001 * q * q
                net.p[k] -= (rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    return net


# ---- the operator -----------------------------------------------------------------------------


def labelled(net: Net, pages: list[list[Block]], vectors: Vectors, most: int = 6000) -> list[np.ndarray]:
    """For each page, which blocks are content. Pages of like length are labelled together."""
    out: list[np.ndarray] = [np.zeros(0, bool)] * len(pages)
    order = sorted((i for i in range(len(pages)) if pages[i]), key=lambda i: len(pages[i]))
    at = 0
    while at < len(order):
        first = at
        while at < len(order) and (at == first or (at + 1 - first) * len(pages[order[at]]) <= most):
            at += 1
        group = order[first:at]
        flat = vectors([b for i in group for b in pages[i]])
        cuts = np.cumsum([len(pages[i]) for i in group])[:-1]
        x, n = padded(np.split(flat, cuts))
        p = net.forward(x, n)
        for row, i in enumerate(group):
            out[i] = p[row, : n[row]] >= 0.5
    return out


def main_text(items: list[Block], keep: np.ndarray) -> str:
    return "\n".join(b.text for b, k in zip(items, keep) if k)


def train(pages: DataFrame, opt: Options = Options()) -> Net | None:
    """Fit on the ``max_pages`` distinct pages whose html has the least hashes."""
    held = pages.where("html IS NOT NULL").select("html", F.xxhash64("html").alias("h"))
    least = [r.h for r in held.select("h").distinct().orderBy("h").limit(opt.max_pages).collect()]
    if not least:
        return None
    chosen = held.where((F.col("h") <= least[-1]) & F.col("h").isin(least)).groupBy("h").agg(F.min("html").alias("html"))
    return fit(sorted(r.html for r in chosen.collect()), opt)


EXTRACTED = "page_id long, url string, text string, n_chars long"


def extract(pages: DataFrame, net: Net | None) -> DataFrame:
    held = pages.sparkSession.sparkContext.broadcast(net)  # a few thousand numbers

    def run(batches):
        vectors = Vectors()
        for whole in batches:
            for first in range(0, whole.num_rows, 500):
                b = whole.slice(first, 500)
                cut = [blocks(t) for t in b.column(2).to_pylist()]
                keep = labelled(held.value, cut, vectors) if held.value is not None else [np.zeros(len(c), bool) for c in cut]
                texts = [main_text(c, k) for c, k in zip(cut, keep)]
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])
        tidy()

    slim = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return slim.mapInArrow(run, EXTRACTED)


def op6_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every page."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html")
    return extract(pages, train(pages))
