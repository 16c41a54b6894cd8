"""Main text of web pages by a recurrent labeller of blocks.

A page becomes a sequence of leaves: runs of text between block-level tags, each with its path of open tags. A two-way
LSTM in NumPy reads the path's hashed tags and class names, hashed words and a few counts of every leaf in
page order, so that each label draws on the whole page; leaves labelled main are joined. The network is fitted, with
fixed seeds, on pages that a generator lays out at random from the usual containers of articles and of everything else."""

from __future__ import annotations

import html as entities
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship

PATH, LAST, WORD, COUNTS = 160, 48, 32, 6
INPUT = PATH + LAST + WORD + COUNTS
HIDDEN = 20
SEED, PAGES, EPOCHS, BATCH, RATE = 3, 1200, 12, 32, 0.01
#: Leaves, padding included, whose vectors are held at once.
CELLS = 8192

#: Their content is no markup, so that only their own end tag ends them.
RAW = "script|style|textarea"
#: Dropped with all they hold; their content is markup.
DROPPED = frozenset("noscript template iframe svg object select".split())
TOKEN = re.compile(rf"<!--.*?(?:-->|\Z)|<({RAW})(?=[\s/>])[^>]*>.*?(?:</\1\s*>|\Z)|<[!?][^>]*>|</?[a-zA-Z][^<>]*>?|[^<]+|<", re.S | re.I)
TAG = re.compile(r"<(/?)([a-zA-Z][a-zA-Z0-9-]*)")
NAMED = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
CLOSES = {"p": {"p"}, "li": {"li", "p"}, "dt": {"dt", "dd", "p"}, "dd": {"dt", "dd", "p"}, "tr": {"tr", "td", "th", "p"}, "td": {"td", "th", "p"}, "th": {"td", "th", "p"}, "option": {"option"}, "body": {"head", "title"}}
ENDS_P = frozenset("address article aside blockquote details div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main nav ol pre section table ul".split())
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())


@lru_cache(100_000)
def _slot(word: str, size: int) -> int:
    h = 2166136261
    for b in word.encode("utf-8", "replace"):
        h = ((h ^ b) * 16777619) & 0xFFFFFFFF
    return (h ^ (h >> 15)) * 2654435761 % 2**32 % size


def leaves(page: str) -> list[tuple[tuple[str, ...], str, int]]:
    """(path, text, characters in links) of every block that has text. Path entries are tags, then .class names.

    A dropped element ends with its own end tag or with that of an element around it; one written <svg/> is empty."""
    out, stack, links, parts, linked = [], [], 0, [], 0
    held: list[str] = []
    # open tags from a dropped element on, and the inline ones around it
    within: list[str] = []
    inline: dict[str, int] = {}

    def flush():
        nonlocal parts, linked
        if parts:
            text = " ".join(entities.unescape("".join(parts)).split())
            if text:
                out.append((tuple(held), text, linked))
        parts, linked = [], 0

    for m in TOKEN.finditer(page):
        s = m.group()
        if s[0] != "<" or s == "<":
            if within:
                continue
            if not parts:
                held = [x for entry in stack for x in entry[1]]
            parts.append(s)
            linked += len(s) if links else 0
            continue
        if m.group(1) or s[1] in "!?":
            if m.group(1) and not within:
                parts.append(" " if parts else "")
            continue
        t = TAG.match(s)
        end, tag = t.group(1), t.group(2).lower()
        if within:
            if not end:
                if tag not in VOID and not s.endswith("/>"):
                    within.append(tag)
                continue
            if tag in within:
                del within[len(within) - 1 - within[::-1].index(tag) :]
                continue
            if not inline.get(tag) and all(tag != entry[0] for entry in stack):
                continue
            within.clear()
        if tag in DROPPED:
            if not end and not s.endswith("/>"):
                within.append(tag)
            if tag in ("noscript", "template"):
                parts.append(" " if parts else "")
            continue
        if tag == "a":
            links = max(0, links + (-1 if end else 1))
        if tag in INLINE:
            if tag == "br":
                parts.append(" " if parts else "")
            elif tag not in VOID:
                inline[tag] = max(0, inline.get(tag, 0) + (-1 if end else 1))
            continue
        flush()
        if end:
            names = [entry[0] for entry in stack]
            if tag in names:
                del stack[len(names) - 1 - names[::-1].index(tag) :]
            continue
        shut = CLOSES.get(tag, {"p"} if tag in ENDS_P else set())
        while stack and stack[-1][0] in shut:
            stack.pop()
        if tag in VOID:
            continue
        named = [x for g in NAMED.findall(s) for x in re.split(r"[^a-z0-9]+", "".join(g).lower()) if x] if "=" in s else []
        stack.append((tag, (tag, *("." + x for x in named))))
    flush()
    return out


def vectors(seq: list, first: int = 0, total: int | None = None) -> np.ndarray:
    """Inputs of leaves, the first of which is that number of so many on the page."""
    x = np.zeros((len(seq), INPUT), np.float32)
    n = total or len(seq)
    for i, (path, text, linked) in enumerate(seq):
        for p in path:
            x[i, _slot(p, PATH)] = 1
        own = [p for p in path[-4:] if p]
        for p in own[-1:] or ["text"]:
            x[i, PATH + _slot("last" + p, LAST)] = 1
        words = text.split(" ")
        slots = [_slot(w.strip(".,;:!?"), WORD) for w in map(str.lower, words)]
        x[i, PATH + LAST : PATH + LAST + WORD] = np.bincount(slots, minlength=WORD) / len(words)
        size = len(text)
        x[i, PATH + LAST + WORD :] = (np.log1p(size) / 6, min(1.0, linked / size), np.log1p(text.count(" ")) / 4, text[-1] in ".!?…\"”", (first + i) / max(1, n - 1), 1)
    return x


class Network:
    """Two LSTMs over a padded batch (pages x leaves x INPUT) and a logistic output on both states and the input."""

    def __init__(self, seed: int = SEED):
        g = np.random.default_rng(seed)
        self.p = {}
        for d in "fb":
            self.p[d + "x"] = (g.normal(0, 1 / np.sqrt(12), (INPUT, 4 * HIDDEN)) * 0.5).astype(np.float32)
            self.p[d + "h"] = g.normal(0, 1 / np.sqrt(HIDDEN), (HIDDEN, 4 * HIDDEN)).astype(np.float32)
            bias = np.zeros(4 * HIDDEN, np.float32)
            bias[HIDDEN : 2 * HIDDEN] = 1
            self.p[d + "c"] = bias
        self.p["o"] = g.normal(0, 0.1, 2 * HIDDEN + INPUT).astype(np.float32)
        self.p["oc"] = np.zeros(1, np.float32)

    @staticmethod
    def _sigmoid(z):
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))

    def _run(self, x, mask, d, trace=None, state=None):
        n, t, _ = x.shape
        h, c = state or (np.zeros((n, HIDDEN), np.float32), np.zeros((n, HIDDEN), np.float32))
        pre = x @ self.p[d + "x"] + self.p[d + "c"]
        out = np.zeros((n, t, HIDDEN), np.float32)
        for k in range(t) if d == "f" else range(t - 1, -1, -1):
            z = pre[:, k] + h @ self.p[d + "h"]
            s = self._sigmoid(z[:, : 3 * HIDDEN])
            i, f, o, g = s[:, :HIDDEN], s[:, HIDDEN : 2 * HIDDEN], s[:, 2 * HIDDEN :], np.tanh(z[:, 3 * HIDDEN :])
            m = mask[:, k : k + 1]
            c2 = f * c + i * g
            th = np.tanh(c2)
            if trace is not None:
                trace.append((k, i, f, o, g, c, th, h, m))
            h, c = m * (o * th) + (1 - m) * h, m * c2 + (1 - m) * c
            out[:, k] = h
        if state is not None:
            state[:] = h, c
        return out

    def scores(self, x, mask):
        """Of every leaf of a padded batch of pages."""
        o = self.p["o"]
        return self._run(x, mask, "f") @ o[:HIDDEN] + self._run(x, mask, "b") @ o[HIDDEN : 2 * HIDDEN] + x @ o[2 * HIDDEN :] + self.p["oc"][0]

    def long_scores(self, seq: list) -> np.ndarray:
        """Of one page of any length: as scores, but the vectors of CELLS leaves at a time are held."""
        n, o = len(seq), self.p["o"]
        out = np.full(n, self.p["oc"][0], np.float32)
        steps = list(range(0, n, CELLS))
        for j, d in enumerate("fb"):
            state = [np.zeros((1, HIDDEN), np.float32), np.zeros((1, HIDDEN), np.float32)]
            for low in steps if d == "f" else reversed(steps):
                x = vectors(seq[low : low + CELLS], low, n)[None]
                out[low : low + CELLS] += (self._run(x, np.ones(x.shape[:2], np.float32), d, state=state) @ o[j * HIDDEN : (j + 1) * HIDDEN])[0]
                if not j:
                    out[low : low + CELLS] += (x @ o[2 * HIDDEN :])[0]
        return out

    def gradient(self, x, mask, y):
        traces = {"f": [], "b": []}
        hs = {d: self._run(x, mask, d, traces[d]) for d in "fb"}
        both = np.concatenate([hs["f"], hs["b"], x], 2)
        dz = (self._sigmoid(both @ self.p["o"] + self.p["oc"][0]) - y) * mask / mask.sum()
        grad = {"o": np.einsum("nt,ntk->k", dz, both), "oc": np.array([dz.sum()], np.float32)}
        for j, d in enumerate("fb"):
            into = dz[:, :, None] * self.p["o"][j * HIDDEN : (j + 1) * HIDDEN]
            dh, dc = np.zeros((len(x), HIDDEN), np.float32), np.zeros((len(x), HIDDEN), np.float32)
            dpre = np.zeros((*x.shape[:2], 4 * HIDDEN), np.float32)
            gh = np.zeros_like(self.p[d + "h"])
            for k, i, f, o, g, c, th, h, m in reversed(traces[d]):
                dh = dh + into[:, k]
                a, keep_h, keep_c = m * dh, (1 - m) * dh, (1 - m) * dc
                dcell = m * dc + a * o * (1 - th**2)
                dall = np.concatenate([dcell * g * i * (1 - i), dcell * c * f * (1 - f), a * th * o * (1 - o), dcell * i * (1 - g**2)], 1)
                dpre[:, k] = dall
                gh += h.T @ dall
                dh, dc = dall @ self.p[d + "h"].T + keep_h, dcell * f + keep_c
            grad[d + "h"] = gh
            grad[d + "x"] = np.einsum("nti,ntk->ik", x, dpre, optimize=True)
            grad[d + "c"] = dpre.sum((0, 1))
        return grad


def _pad(items: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    t = max(len(v) for v in items)
    x, mask = np.zeros((len(items), t, INPUT), np.float32), np.zeros((len(items), t), np.float32)
    for i, v in enumerate(items):
        x[i, : len(v)], mask[i, : len(v)] = v, 1
    return x, mask


#: Class names that the generator gives to containers of the article and of other kinds; fixed values.
GOOD = "article content post entry main story body text article-body post-content entry-content main-content story-body".split()
BAD = "ad ads advert advertisement sponsored promo banner sidebar side rail widget related recommended share social menu nav navbar breadcrumb breadcrumbs footer foot header masthead topbar cookie cookies consent notice alert popup modal newsletter subscribe signup login search comments comment reply replies discussion copyright legal tags pagination pager byline-links toolbar".split()
PHRASES = "Home|About us|Contact|Subscribe to our newsletter|Read more|Share this|All rights reserved.|Privacy policy|We use cookies.|Accept|Log in|Search|Related articles|Leave a comment|Reply|Next page|Sponsored|Terms of use|Sign up|Most read|Popular|Copyright 2004|Great article, thanks!|I don't agree.".split("|")
#: Share of the containers whose names tell nothing, on pages (every second one) where names are of the site's own making.
NAMELESS = 0.75


def generated(seed: int, pages: int) -> list[tuple[list, np.ndarray]]:
    """Pages as (leaves, labels): an article in a random layout with random surroundings, words made of random syllables."""
    r = np.random.default_rng(seed)
    syllables = ["".join(p) for p in zip(r.choice(list("bcdfghlmnprstvzé"), 300), r.choice(list("aeiouáüe"), 300), r.choice(["", "n", "r", "s", "th", "l"], 300), strict=True)]
    pick = lambda xs: xs[int(r.integers(len(xs)))]

    def words(a, b):
        return " ".join("".join(r.choice(syllables, int(r.integers(1, 4)))) for _ in range(int(r.integers(a, b))))

    def sentence(a=1, b=60):
        return words(a, b).capitalize() + pick([".", ".", ".", "?", "", "!!", "&amp;&amp;"])

    def mark(s, good):
        return f"\x01{int(good)}{s}"

    own_names = False

    def named(known):
        """A class name: a known one, or where the site has its own, one that nobody has seen."""
        if not own_names or r.random() > NAMELESS:
            return pick(known)
        return pick(["-", "__", " "]).join("".join(r.choice(syllables, 2)) for _ in range(int(r.integers(1, 3))))

    def boiler(depth=0):
        kind, name = int(r.integers(8)), named(BAD)
        text = lambda: mark(pick(PHRASES) if r.random() < 0.4 else sentence(1, 30), False)
        tag = pick(["div", "div", "section", "aside", "nav", "header", "footer", "form"])
        own = f' class="{name}"' if tag in ("div", "section") or r.random() < 0.4 else ""
        if r.random() < 0.2:
            own = own.replace("class", "id")
        if kind <= 2:
            inner = "<ul>" + "".join(f'<li><a href="/x">{text()}</a></li>' for _ in range(int(r.integers(1, 9)))) + "</ul>"
            tag, own = ("nav", pick(["", ' class="menu"'])) if r.random() < (0.2 if own_names else 0.6) else (tag, own)
        elif kind == 3:
            tag, own = "footer", pick(["", ' class="foot"'])
            inner = mark("&copy; " + words(1, 4), False) + (f"<p>{text()}</p>" if r.random() < 0.5 else "")
        elif kind == 4:
            tag, own = pick([("section", ' id="comments"'), ("div", ' class="comments"'), ("div", ' class="comment-list"')])
            each = "comment"
            if own_names:
                tag, own, each = "div", f' class="{named(["comments"])}"', named(["comment"])
            inner = "".join(f'<div class="{each}"><p>{mark(sentence(2, 40), False)}</p></div>' for _ in range(int(r.integers(1, 5))))
        elif kind == 5:
            tag, own, inner = "form", "", f"<label>{text()}</label><p>{text()}</p><button>{text()}</button>"
        elif kind == 6 and r.random() < 0.5:
            tag, own = "header", pick(["", ' class="site"'])
            inner = f"<{(t := pick(['h1', 'h2', 'p', 'div']))}>{text()}</{t}>" + (f"<p>{text()}</p>" if r.random() < 0.3 else "")
        else:
            inner = text() if r.random() < 0.5 else f"<h3>{text()}</h3>" + "".join(f"<p>{text()}</p>" for _ in range(int(r.integers(1, 4))))
        return f"<{tag}{own}>{inner}</{tag}>"

    def article():
        parts = [f"<{pick(['h1', 'h1', 'h2'])}>{mark(sentence(2, 12), True)}</h1>".replace("</h1>", "")] if r.random() < 0.9 else []
        parts = [p + "</" + p[1:3] + ">" for p in parts]
        for _ in range(int(r.integers(0, 14))):
            k = int(r.integers(10))
            if k == 0:
                parts.append(f"<h2>{mark(sentence(1, 8), True)}</h2>")
            elif k == 1:
                parts.append("<ul>" + "".join(f"<li>{mark(sentence(1, 20), True)}</li>" for _ in range(int(r.integers(1, 6)))) + "</ul>")
            elif k == 2:
                parts.append(f"<blockquote><p>{mark(sentence(), True)}</p></blockquote>")
            elif k == 3:
                parts.append(f"<p><b>{mark(sentence(1, 30), True)}<br>")
            elif k == 4:
                parts.append(boiler() if r.random() < 0.6 else f'<{(t := pick(["div", "aside", "p"]))} class="{named(BAD)}">{mark(sentence(1, 20), False)}</{t}>')
            elif k == 5 and r.random() < 0.3:
                parts.append(f"<table><tr><td>{mark(words(1, 4), True)}</td><td>{mark(words(1, 4), True)}</td></tr></table>")
            elif k == 6 and r.random() < 0.3:
                parts.append(f"<figure><figcaption>{mark(sentence(2, 12), True)}</figcaption></figure>")
            else:
                parts.append(f"<p>{mark(sentence(1, 1 + 3 ** int(r.integers(1, 5))), True)}</p>")
        kind = int(r.integers(6))
        inner = "".join(parts)
        if kind <= 2:
            return f"<article>{inner}</article>"
        if kind == 3:
            return f"<main>{inner}</main>"
        if kind == 4:
            return f'<main><article><div class="{named(GOOD)}">{inner}</div></article></main>'
        return f'<{(t := pick(["div", "div", "section"]))} {pick(["class", "id"])}="{named(GOOD)}">{inner}</{t}>'

    out = []
    for number in range(pages):
        own_names = number % 2 == 1
        before, after = ("".join(boiler() for _ in range(int(r.integers(0, 4)))) for _ in range(2))
        body = before + article() + after
        if own_names and r.random() < 0.1:
            body = "<table>" + "".join(f"<tr><td>{x}</td></tr>" for x in (before, article(), after)) + "</table>"
        if r.random() < 0.2:
            body = f'<div class="{pick(["page", "wrapper", "container", "site", "layout"])}">{body}</div>'
        title = f"<title>{mark(sentence(2, 12), False)}</title>" if r.random() < 0.7 else ""
        page = f"<html><head>{title}</head><body>{body}</body></html>" if r.random() < 0.75 else f"{title}<body>{body}" if r.random() < 0.5 else body
        seq = leaves(page)
        y = np.array(["\x011" in t for _, t, _ in seq], np.float32)
        out.append(([(p, re.sub("\x01.", "", t) or "x", n) for p, t, n in seq], y))
    return [o for o in out if o[0]]


@lru_cache(2)
def fitted(seed: int = SEED, pages: int = PAGES, epochs: int = EPOCHS) -> Network:
    data = [(vectors(seq), y) for seq, y in generated(seed, pages)]
    data.sort(key=lambda d: len(d[0]))
    groups = [data[i : i + BATCH] for i in range(0, len(data), BATCH)]
    net, g = Network(seed), np.random.default_rng(seed)
    first, second, step = {k: 0.0 for k in net.p}, {k: 0.0 for k in net.p}, 0
    for epoch in range(epochs):
        for i in g.permutation(len(groups)):
            x, mask = _pad([v for v, _ in groups[i]])
            y = np.zeros(mask.shape, np.float32)
            for j, (_, own) in enumerate(groups[i]):
                y[j, : len(own)] = own
            step += 1
            for k, d in net.gradient(x, mask, y).items():
                d = d / max(1.0, float(np.sqrt((d**2).sum())))
                first[k] = 0.9 * first[k] + 0.1 * d
                second[k] = 0.999 * second[k] + 0.001 * d**2
                rate = RATE * (1 if epoch < epochs * 2 // 3 else 0.3)
                net.p[k] = (net.p[k] - rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    return net


def labelled(net: Network, pages: list[str]) -> list[list[tuple[str, bool]]]:
    """(text, main or not) of every leaf of every page."""
    seqs = [leaves(p) for p in pages]
    out: list = [[] for _ in pages]
    order, low = sorted((i for i in range(len(pages)) if seqs[i]), key=lambda i: len(seqs[i])), 0
    while low < len(order):
        high = low + 1
        while high < len(order) and (high + 1 - low) * len(seqs[order[high]]) <= CELLS:
            high += 1
        own, low = order[low:high], high
        if len(seqs[own[0]]) > CELLS:
            z = net.long_scores(seqs[own[0]])[None]
        else:
            z = net.scores(*_pad([vectors(seqs[i]) for i in own]))
        for j, i in enumerate(own):
            out[i] = [(leaf[1], bool(z[j, k] > 0)) for k, leaf in enumerate(seqs[i])]
    return out


def _steps(body: pa.Array, rows: int = 512, size: int = 4_000_000):
    """Row ranges of so many rows or bytes; a longer page is one of its own."""
    low, held = 0, 0
    for k, n in enumerate(pc.binary_length(body).to_pylist()):
        if k > low and (held + n > size or k - low >= rows):
            yield low, k
            low, held = k, 0
        held += n
    if low < len(body):
        yield low, len(body)


def extract(pages: DataFrame, key: str = "page_id", html: str = "html", keep: tuple[str, ...] = ("url",)) -> DataFrame:
    """(key, *keep, text, n_chars) of every page; text is empty for a null or empty page or one without main blocks."""
    ship(pages.sparkSession)
    sent = pages.sparkSession.sparkContext.broadcast(fitted().p)  # about 30,000 numbers

    def run(batches):
        net = Network()
        net.p = sent.value
        for batch in batches:
            for low, high in _steps(batch.column(batch.num_columns - 1)):
                part = batch.slice(low, high - low)
                body = part.column(batch.num_columns - 1).to_pylist()
                texts = ["\n".join(t for t, main in page if main) for page in labelled(net, body)]
                yield pa.record_batch([*part.columns[:-1], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], [*batch.schema.names[:-1], "text", "n_chars"])

    kinds = dict(pages.dtypes)
    held = pages.select(key, *keep, F.coalesce(F.col(html), F.lit("")).alias("_html"))
    return held.mapInArrow(run, ", ".join(f"{c} {kinds[c]}" for c in (key, *keep)) + ", text string, n_chars long")
