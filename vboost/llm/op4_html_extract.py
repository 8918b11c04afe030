"""HTML extraction: a linear-chain conditional random field over a page's leaf blocks.

A page is cut into leaf blocks: runs of text between block-level tags, with the tags and class words of their
ancestors. The field has two labels, kept and dropped; its features are ancestor tags, class and id words, and
figures of the text. It is trained by stochastic gradient on labelled pages, which are generated here in many
layouts, and decoded by Viterbi on the executors. Its weights are a few thousand numbers.
"""

from __future__ import annotations

import html
import math
import random
import re
from collections import defaultdict
from collections.abc import Container, Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import small_batches, table

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([A-Za-z][A-Za-z0-9:-]*)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*)/?>|<[!?/][^>]*>", re.S)
_NAMES = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_HIDDEN = re.compile(r"\bhidden\b|display\s*:\s*none", re.I)
#: Elements whose text is never shown, elements within a line, and elements without an end.
UNSEEN = frozenset("script style noscript template head title svg iframe object canvas math audio video".split())
INLINE = frozenset("a abbr b bdi bdo big br cite code del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
CLOSES_P = frozenset("address article aside blockquote div dl fieldset figure footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())


@dataclass(slots=True)
class Block:
    text: str
    marks: tuple[str, ...]
    linked: int


def _marks_of(tag: str, attributes: str) -> tuple[str, ...]:
    return _read_marks(tag, attributes) if len(attributes) > 400 else _short_marks(tag, attributes)


def _read_marks(tag: str, attributes: str) -> tuple[str, ...]:
    """The element's name, every word of its class, id and role, and whether it is hidden."""
    words = [w for m in _NAMES.finditer(attributes) for w in re.split(r"[^a-z]+", (m[1] or m[2] or m[3] or "").lower()) if w]
    return (f"t={tag}", *(f"c={w}" for w in dict.fromkeys(words)), *(("hidden",) if _HIDDEN.search(attributes) else ()))


_short_marks = lru_cache(maxsize=20_000)(_read_marks)


def leaf_blocks(page: str, known: Container[str] | None = None) -> list[Block]:
    """The page's blocks in order: text with references decoded and white space runs as one space, never empty.

    known: marks that a model has weights for; others add nothing to a block's score and are left out, so a block's
    marks stay few however deep it stands. Each open element holds the marks of all elements around it.
    """
    out: list[Block] = []
    stack: list[tuple[str, tuple[str, ...], str]] = []  # name, marks down to here, nearest block element
    open_tags: dict[str, int] = defaultdict(int)
    pieces: list[str] = []
    linked = 0
    marks: tuple[str, ...] = ()
    at = 0

    def pop() -> None:
        open_tags[stack.pop()[0]] -= 1

    def end_block() -> None:
        nonlocal pieces, linked
        if pieces:
            text = " ".join(html.unescape("".join(pieces)).split())
            if text:
                out.append(Block(text, marks, linked))
            pieces, linked = [], 0

    def take(piece: str) -> None:
        nonlocal marks, linked
        if not pieces and not piece.strip():
            return
        if not pieces:
            around = stack[-1] if stack else ("", (), "none")
            marks = (*around[1], f"p={around[2]}")
        pieces.append(piece)
        if open_tags["a"]:
            linked += len(piece)

    while at < len(page):
        m = _TAG.search(page, at)
        if m is None:
            take(page[at:])
            break
        if m.start() > at:
            take(page[at : m.start()])
        at = m.end()
        if m[2] is None:
            continue
        tag = m[2].lower()
        if m[1]:
            if tag not in INLINE:
                end_block()
            if open_tags[tag]:
                while stack[-1][0] != tag:
                    pop()
                pop()
            continue
        if tag in UNSEEN:
            if tag not in INLINE:
                end_block()
            if not m[0].endswith("/>"):
                close = re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(page, at)
                at = close.end() if close else len(page)
            continue
        if tag == "br":
            take(" ")
            continue
        if tag not in INLINE:
            end_block()
            same = {"li": ("li",), "tr": ("tr",), "td": ("td", "th"), "th": ("td", "th"), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "option": ("option",)}.get(tag, ("p",) if tag in CLOSES_P else ())
            for k in range(len(stack) - 1, -1, -1):  # an open element of the kind ends here, unless its container began since
                if stack[k][0] in same:
                    while len(stack) > k:
                        pop()
                    break
                if stack[k][0] not in INLINE:
                    break
        if tag not in VOID and not m[0].endswith("/>"):
            _, held, outer = stack[-1] if stack else ("", (), "none")
            new = tuple(x for x in _marks_of(tag, m[3] or "") if x not in held and (known is None or x in known))
            stack.append((tag, held + new if new else held, outer if tag in INLINE else tag))
            open_tags[tag] += 1
    end_block()
    return out


def block_features(blocks: list[Block]) -> list[list[str]]:
    """Names of each block's features; place and neighbours are left to the chain."""
    out = []
    for i, b in enumerate(blocks):
        n, words = len(b.text), b.text.count(" ") + 1
        share = b.linked / max(n, 1)
        out.append(
            [
                *b.marks,
                "bias",
                f"words={min(int(math.log2(words)), 7)}",
                f"linked={'none' if share == 0 else 'some' if share < 0.5 else 'most'}",
                f"ends={'stop' if b.text[-1] in '.!?…' else 'other'}",
                f"copyright={'©' in b.text}",
                f"edge={'first' if i == 0 else 'last' if i == len(blocks) - 1 else 'inner'}",
            ]
        )
    return out


@dataclass
class ChainField:
    """weights: feature -> (dropped, kept); moves[a][b]: from label a to label b; first: the first label."""

    weights: dict[str, list[float]] = field(default_factory=dict)
    moves: list[list[float]] = field(default_factory=lambda: [[0.0, 0.0], [0.0, 0.0]])
    first: list[float] = field(default_factory=lambda: [0.0, 0.0])

    def emissions(self, features: list[list[str]]) -> list[tuple[float, float]]:
        out = []
        none = (0.0, 0.0)
        get = self.weights.get
        for names in features:
            a = b = 0.0
            for f in names:
                w = get(f, none)
                a += w[0]
                b += w[1]
            out.append((a, b))
        return out

    def decode(self, features: list[list[str]]) -> list[int]:
        """The most likely labels."""
        e = self.emissions(features)
        if not e:
            return []
        best = [self.first[0] + e[0][0], self.first[1] + e[0][1]]
        back = []
        m = self.moves
        for x in e[1:]:
            from0 = 0 if best[0] + m[0][0] >= best[1] + m[1][0] else 1
            from1 = 0 if best[0] + m[0][1] > best[1] + m[1][1] else 1
            back.append((from0, from1))
            best = [best[from0] + m[from0][0] + x[0], best[from1] + m[from1][1] + x[1]]
        y = [0 if best[0] > best[1] else 1]
        for b in reversed(back):
            y.append(b[y[-1]])
        return y[::-1]

    def gradients(self, features: list[list[str]], labels: list[int]) -> tuple[list[tuple[float, float]], list[list[float]]]:
        """Observed minus expected labels of each block and moves, by forward and backward sums."""
        e, m = self.emissions(features), self.moves
        top = lambda a, b: max(a, b) + math.log1p(math.exp(-abs(a - b)))
        f = [(self.first[0] + e[0][0], self.first[1] + e[0][1])]
        for x in e[1:]:
            p = f[-1]
            f.append(tuple(top(p[0] + m[0][y], p[1] + m[1][y]) + x[y] for y in (0, 1)))
        g = [(0.0, 0.0)]
        for x in reversed(e[1:]):
            p = g[-1]
            g.append(tuple(top(m[y][0] + x[0] + p[0], m[y][1] + x[1] + p[1]) for y in (0, 1)))
        g.reverse()
        z = top(*f[-1])
        nodes = []
        for i, y in enumerate(labels):
            p1 = math.exp(min(0.0, f[i][1] + g[i][1] - z))
            nodes.append(((1.0 - y) - (1.0 - p1), y - p1))
        moved = [[0.0, 0.0], [0.0, 0.0]]
        for i in range(1, len(e)):
            moved[labels[i - 1]][labels[i]] += 1
            for a in (0, 1):
                for b in (0, 1):
                    moved[a][b] -= math.exp(min(0.0, f[i - 1][a] + m[a][b] + e[i][b] + g[i][b] - z))
        return nodes, moved


def train_field(pages: list[tuple[list[list[str]], list[int]]], epochs: int = 8, rate: float = 0.3, ridge: float = 1e-4, seed: int = 7) -> ChainField:
    """Conditional likelihood by AdaGrad steps, one for each page."""
    model, squares, order = ChainField(), defaultdict(lambda: [1e-6, 1e-6]), random.Random(seed)
    move_squares = [[1e-6, 1e-6], [1e-6, 1e-6]]
    pages = [p for p in pages if p[0]]
    for _ in range(epochs):
        order.shuffle(pages)
        for features, labels in pages:
            nodes, moved = model.gradients(features, labels)
            sums: dict[str, list[float]] = {}
            for names, d in zip(features, nodes):
                for f in names:
                    s = sums.setdefault(f, [0.0, 0.0])
                    s[0] += d[0]
                    s[1] += d[1]
            for f, d in sums.items():
                w, q = model.weights.setdefault(f, [0.0, 0.0]), squares[f]
                for y in (0, 1):
                    step = d[y] - ridge * w[y]
                    q[y] += step * step
                    w[y] += rate * step / math.sqrt(q[y])
            for a in (0, 1):
                model.first[a] += 0.05 * nodes[0][a]
                for b in (0, 1):
                    move_squares[a][b] += moved[a][b] ** 2
                    model.moves[a][b] += rate * moved[a][b] / math.sqrt(move_squares[a][b])
    return model


#: Class words by the kind of part that carries them in generated pages.
KINDS = {
    "menu": ("nav div ul", "nav menu navbar navigation breadcrumb breadcrumbs topnav links toc"),
    "header": ("header div", "header masthead banner top branding logo site"),
    "footer": ("footer div", "footer bottom copyright legal colophon credits"),
    "sidebar": ("aside div section", "sidebar widget related recommended trending popular aside rail more"),
    "advert": ("div aside section ins", "ad ads advert advertisement sponsor sponsored promo banner adsbygoogle partner"),
    "notice": ("div section dialog", "cookie consent notice alert gdpr popup modal overlay privacy banner message"),
    "form": ("form div section", "form search newsletter subscribe signup login contact register"),
    "comments": ("section div ol", "comments comment replies reply respond discussion thread disqus reader feedback"),
    "share": ("div ul", "share social sharing follow tags meta byline pagination pager"),
}
BODY = ("article main div section", "article content main post entry story body text page single")


def labelled_page(rng: random.Random) -> tuple[str, list[int]]:
    """A generated page and the label of each of its blocks (1: of the article)."""
    labels: list[int] = []
    word = lambda: "".join(rng.choice("ka to ri men sol an ber ti vo lu er st in da".split()) for _ in range(rng.randint(1, 4)))
    words = lambda a, b: " ".join(word() for _ in range(rng.randint(a, b)))

    def say(text: str, keep: int) -> str:
        labels.append(keep)
        return text

    def prose(keep: int, low: int = 3, high: int = 60) -> str:
        inner = words(low, high).capitalize() + rng.choice([".", ".", ".", "!", "?", ""])
        if rng.random() < 0.25:
            inner = re.sub(r" (\w+) ", lambda m: rng.choice([" <a href='/x'>{}</a> ", " <b>{}</b> ", " <em>{}</em> "]).format(m[1]), inner, count=1)
        return say(inner, keep)

    def attributes(names: str, often: float) -> str:
        if rng.random() > often:
            return ""
        n = rng.choice(names.split())
        joined = rng.choice([n, n + "-" + rng.choice(["box", "area", "wrap", "list", "item", "1"]), rng.choice(["site", "page", "the"]) + "-" + n])
        return f' {rng.choice(["class", "class", "id"])}="{joined}"'

    def part(kind: str) -> str:
        tags, names = KINDS[kind]
        tag = rng.choice(tags.split())
        a = attributes(names, 0.97 if tag in ("div", "section", "ul", "ol", "ins", "dialog") else 0.4)
        if kind in ("menu", "share", "sidebar") and rng.random() < 0.7 or tag in ("ul", "ol"):
            items = "".join(f"<li><a href='/p'>{say(words(1, 3), 0)}</a></li>" for _ in range(rng.randint(2, 7)))
            inner = items if tag in ("ul", "ol") else f"<ul>{items}</ul>"
        elif kind == "form":
            inner = f"<p>{prose(0, 2, 9)}</p><input name='q'><button>{say(words(1, 2), 0)}</button>"
        elif kind == "comments":
            inner = f"<h3>{say(words(1, 2), 0)}</h3>" + "".join(f"<div class='comment'><p>{prose(0, 3, 40)}</p></div>" for _ in range(rng.randint(1, 4)))
        elif kind == "footer":
            inner = f"<p>{say(rng.choice(['&copy; ', '© 2020 ', '']) + words(2, 8), 0)}</p>"
        elif kind == "header":
            inner = rng.choice(["<div class='logo'>{}</div>", "<p>{}</p>", "<a href='/'>{}</a>", "<h2>{}</h2>"]).format(say(words(1, 5), 0))
        else:
            inner = rng.choice(["<p>{}</p>", "{}", "<span>{}</span>"]).format(prose(0, 2, 25))
        return f"<{tag}{a}>{inner}</{tag}>"

    def article() -> str:
        tag = rng.choice(BODY[0].split())
        out = [f"<{tag}{attributes(BODY[1], 0.9 if tag in ('div', 'section') else 0.4)}>", f"<h1>{say(words(2, 8), 1)}</h1>" if rng.random() < 0.8 else ""]
        for _ in range(rng.randint(2, 10)):
            shape = rng.random()
            if shape < 0.66:
                out.append(rng.choice(["<p>{}</p>", "<p>{}</p>", "<p>{}", "<div>{}</div>", "<p><b>{}<br></p>"]).format(prose(1, 1, 80)))
            elif shape < 0.72:
                out.append(f"<h2>{say(words(1, 6), 1)}</h2>")
            elif shape < 0.78:
                out.append("<ul>" + "".join(f"<li>{prose(1, 2, 15)}</li>" for _ in range(rng.randint(2, 4))) + "</ul>")
            elif shape < 0.81:
                out.append(f"<blockquote>{prose(1, 4, 30)}</blockquote>")
            elif shape < 0.84:
                out.append("<table><tr>" + "".join(f"<td>{say(words(1, 3), 1)}</td>" for _ in range(3)) + "</tr></table>")
            else:
                out.append(part(rng.choice(["advert", "share", "sidebar", "form", "notice"])))
        if rng.random() < 0.15:
            out.append(part("comments"))
        return "".join(out) + f"</{tag}>"

    before = [part(k) for k in rng.sample(["notice", "header", "menu", "advert", "form", "share"], rng.randint(1, 4))]
    middle = [article()]
    after = [part(k) for k in rng.sample(["sidebar", "comments", "advert", "menu", "form", "footer", "notice", "share"], rng.randint(1, 4))]
    return f"<html><head><title>{words(2, 6)}</title><script>x='<p>'</script></head><body>" + "".join(before + middle + after) + "</body></html>", labels


def labelled_pages(n: int = 600, seed: int = 11) -> list[tuple[list[list[str]], list[int]]]:
    """Features and labels of generated pages; a page whose blocks do not match its labels is left out."""
    rng, out = random.Random(seed), []
    for _ in range(n):
        page, labels = labelled_page(rng)
        blocks = leaf_blocks(page)
        if len(blocks) == len(labels):
            out.append((block_features(blocks), labels))
    return out


@lru_cache(maxsize=1)
def default_field() -> ChainField:
    return train_field(labelled_pages())


def main_text(page: str | None, model: ChainField) -> tuple[str, list[tuple[str, int]]]:
    """The kept blocks joined by line feeds, and every block with its label."""
    blocks = leaf_blocks(page or "", model.weights)
    labels = model.decode(block_features(blocks))
    return "\n".join(b.text for b, y in zip(blocks, labels) if y), [(b.text, y) for b, y in zip(blocks, labels)]


def _extract(model: ChainField):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                some = batch.slice(at, 512)
                texts = [main_text(x, model)[0] for x in some.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([some.column(0), some.column(1), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return run


def extract_pages(pages: DataFrame, model: ChainField | None = None) -> DataFrame:
    """page_id, url, text, n_chars for every row of pages (page_id, url, html).

    Null or empty html, and pages whose every block is dropped, have an empty text. Repeated rows stay; an empty
    table gives no rows; other columns are ignored.
    """
    small_batches(pages.sparkSession)
    rows = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string"))
    return rows.mapInArrow(_extract(model or default_field()), "page_id long, url string, text string, n_chars long")


def op4_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main text of every page."""
    return extract_pages(table(spark, sf_dir, "pages"))
