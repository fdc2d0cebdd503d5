"""Main text of web pages by a linear-chain conditional random field over DOM leaf blocks.

A page is cut into leaf blocks: runs of text between the tags that start or end a block. A block's features are
its ancestors' tags, the words of their class, id and role attributes, and its text (length, share of linked
characters, stops, marks, place in the page). The field has two labels, main text or not, one weight for each
feature and label and one for each pair of neighbouring labels. It is trained here, on pages that
:mod:`training_pages` writes with their labels, by gradient ascent on the likelihood, and decoded by Viterbi.

Defined results: null, empty or markup-only html gives an empty text. Unclosed and stray tags, and a cut-off
end, are read as far as they go; a button, drawing or frame that is closed in itself or by nothing hides no text. White space inside a block is one space, blocks are joined by one line feed
in page order; blocks without text don't exist. Nothing is capped. Rows that repeat, and null ids or urls, are
passed through. Only page_id, url and html are read.
"""

from __future__ import annotations

import functools
import re
from html.parser import HTMLParser

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

FEATURE_BITS = 13
#: Tags by how they cut text.
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr".split())
#: Elements whose text isn't the page's. What stands in one of ``LOOSE`` that nothing closes is read.
SILENT = frozenset("script style template noscript title textarea select option button svg math iframe object canvas audio video datalist".split())
LOOSE = SILENT - frozenset("script style template noscript title textarea option".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
CLOSES = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
ENDS_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
SCOPE = frozenset("ul ol dl table td th article section div aside main nav header footer body form".split())
REGIONS = frozenset("article main aside nav header footer section form div body".split())
TOKEN = re.compile(r"[a-z]+")


class Blocks(HTMLParser):
    """Leaf blocks: (text, linked characters, open tags with their attribute words)."""

    def __init__(self):
        super().__init__(convert_charrefs=True)
        self.stack: list[tuple[str, tuple[str, ...]]] = []
        self.marks: list[int] = []  # blocks before each open tag
        self.parts: list[str] = []
        self.linked = 0
        self.out: list[tuple[str, int, list]] = []

    def cut(self) -> None:
        text = " ".join("".join(self.parts).split())
        if text:
            self.out.append((text, self.linked, self.stack.copy()))
        self.parts, self.linked = [], 0

    def pop_to(self, at: int, closed: bool = False) -> None:
        """Close the tags from a place on; closed: by the end tag of the first of them."""
        self.cut()
        for k in range(len(self.stack) - 1, at - 1, -1):
            tag = self.stack[k][0]
            if tag in SILENT and (tag not in LOOSE or (closed and k == at)):
                del self.out[self.marks[k] :]
        del self.stack[at:], self.marks[at:]

    def close_open(self, tags) -> None:
        for at in range(len(self.stack) - 1, -1, -1):
            if self.stack[at][0] in tags:
                return self.pop_to(at)
            if self.stack[at][0] in SCOPE:
                return None
        return None

    def handle_starttag(self, tag, attrs):
        if tag not in INLINE:
            self.cut()
            if tag in ENDS_P:
                self.close_open({"p"})
            if tag in CLOSES:
                self.close_open(CLOSES[tag])
        elif tag == "br":
            self.parts.append(" ")
        if tag not in VOID:
            words = tuple(w for k, v in attrs if v and k in ("class", "id", "role", "itemprop", "aria-label") for w in TOKEN.findall(re.sub(r"([a-z])([A-Z])", r"\1 \2", v).lower()))
            self.stack.append((tag, words))
            self.marks.append(len(self.out))

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag in SILENT:  # closed in itself
            self.pop_to(len(self.stack) - 1, True)

    def handle_endtag(self, tag):
        for at in range(len(self.stack) - 1, -1, -1):
            if self.stack[at][0] == tag:
                if tag in INLINE:
                    del self.stack[at], self.marks[at]
                else:
                    self.pop_to(at, True)
                return
        if tag not in INLINE:
            self.cut()

    def handle_data(self, data):
        self.parts.append(data)
        if any(t == "a" for t, _ in self.stack):
            self.linked += len(data.strip())


def leaf_blocks(html: str | None) -> list[tuple[str, int, list]]:
    parser = Blocks()
    parser.feed(html or "")
    parser.close()
    parser.pop_to(0)
    return parser.out


@functools.lru_cache(1 << 16)
def _slot(feature: str) -> int:
    import zlib

    return zlib.crc32(feature.encode()) & ((1 << FEATURE_BITS) - 1)


def _bin(n: int) -> int:
    return min(n, 1 << 14).bit_length()


def features(blocks: list[tuple[str, int, list]]) -> list[list[int]]:
    """The slots of each block's features."""
    out, last = [], len(blocks) - 1
    for i, (text, linked, stack) in enumerate(blocks):
        n, tags = len(text), [t for t, _ in stack]
        words, stops = text.count(" ") + 1, sum(map(text.count, ".!?,;"))
        leaf = next((t for t in reversed(tags) if t not in INLINE), "")
        names = {f"tag {t}" for t in tags if t not in INLINE} | {f"word {w}" for _, ws in stack for w in ws}
        names |= {"one", f"leaf {leaf}", f"words {_bin(words)}", f"links {int(4 * min(1, linked / n))}", f"stops {min(4, 10 * stops // words)}", f"end {text[-1] in '.!?…”»'}"}
        names |= {f"depth {min(9, len(tags))}", f"first {i == 0}", f"last {i == last}", f"copy {'©' in text}", f"leaf {leaf} words {_bin(words) // 3}", f"linked {leaf} {linked * 2 > n}"}
        near = next((k for k in range(len(stack) - 1, -1, -1) if tags[k] in REGIONS), 0)
        if stack:
            names |= {f"near {tags[near]} {' '.join(stack[near][1][:2])}", f"near {tags[near]} plain {not any(ws for _, ws in stack[near:])} leaf {leaf}"}
        out.append([_slot(x) for x in names])
    return out


class Field:
    """Weights of features (slots by labels), of neighbouring labels, and of the first label."""

    def __init__(self, emit: np.ndarray, move: np.ndarray, first: np.ndarray):
        self.emit, self.move, self.first = emit, move, first

    def decode(self, slots: list[list[int]]) -> np.ndarray:
        """The best labels, by Viterbi."""
        if not slots:
            return np.empty(0, int)
        lens = np.fromiter(map(len, slots), np.int64, len(slots))
        score = np.add.reduceat(self.emit[np.concatenate(slots)], np.cumsum(lens) - lens, axis=0)
        (m00, m01), (m10, m11) = self.move.tolist()
        a, b = (self.first + score[0]).tolist()
        back = []
        for s0, s1 in score[1:].tolist():
            from0, from1 = a + m00 < b + m10, a + m01 < b + m11
            back.append((from0, from1))
            a, b = (b + m10 if from0 else a + m00) + s0, (b + m11 if from1 else a + m01) + s1
        label = int(b > a)
        out = [label]
        for step in reversed(back):
            label = int(step[label])
            out.append(label)
        return np.array(out[::-1])


def train(pages: list[tuple[list[list[int]], np.ndarray]], rounds: int = 60, rate: float = 0.5, decay: float = 1e-4) -> Field:
    """A field from pages (slots of each block, labels), by batch ascent with per-weight steps."""
    size, most = 1 << FEATURE_BITS, max(len(y) for _, y in pages)
    emit, move, first = np.zeros((size, 2)), np.zeros((2, 2)), np.zeros(2)
    page = np.concatenate([np.full(sum(map(len, x)), k) for k, (x, _) in enumerate(pages)])
    place = np.concatenate([np.repeat(np.arange(len(x)), [len(s) for s in x]) for x, _ in pages])
    slot = np.concatenate([np.concatenate(x) for x, _ in pages])
    real = np.zeros((len(pages), most), bool)
    gold = np.zeros((len(pages), most), np.int64)
    for k, (_, y) in enumerate(pages):
        real[k, : len(y)], gold[k, : len(y)] = True, y
    onehot = np.eye(2)[gold] * real[..., None]
    want_move = np.einsum("pia,pib->ab", onehot[:, :-1], onehot[:, 1:])
    squares = [np.full_like(w, 1e-6) for w in (emit, move, first)]
    for _ in range(rounds):
        score = np.zeros((len(pages), most, 2))
        np.add.at(score, (page, place), emit[slot])
        fore, back = np.zeros_like(score), np.zeros_like(score)
        fore[:, 0] = first + score[:, 0]
        for i in range(1, most):
            step = np.logaddexp.reduce(fore[:, i - 1, :, None] + move, axis=1) + score[:, i]
            fore[:, i] = np.where(real[:, i, None], step, fore[:, i - 1])
        for i in range(most - 2, -1, -1):
            step = np.logaddexp.reduce(move + (score[:, i + 1] + back[:, i + 1])[:, None, :], axis=2)
            back[:, i] = np.where(real[:, i + 1, None], step, 0)
        total = np.logaddexp.reduce(fore[:, -1], axis=1)
        marginal = np.exp(fore + back - total[:, None, None]) * real[..., None]
        pair = fore[:, :-1, :, None] + move + (score[:, 1:] + back[:, 1:])[:, :, None, :] - total[:, None, None, None]
        got_move = (np.exp(np.minimum(pair, 0)) * real[:, 1:, None, None]).sum(axis=(0, 1))
        up = np.zeros_like(emit)
        np.add.at(up, slot, (onehot - marginal)[page, place])
        ups = (up - decay * len(pages) * emit, want_move - got_move, (onehot - marginal)[:, 0].sum(axis=0))
        for w, g, q in zip((emit, move, first), ups, squares):
            q += g * g
            w += rate * g / np.sqrt(q)
    return Field(emit, move, first)


@functools.lru_cache(4)
def trained(pages: int = 800, seed: int = 7) -> Field:
    """The field trained on so many labelled pages (a parameter; the pages don't depend on the input)."""
    from .training_pages import labelled_pages

    rows = []
    for html, labels in labelled_pages(pages, seed):
        blocks = leaf_blocks(html)
        rows.append((features(blocks), np.array([labels(b[0]) for b in blocks])))
    return train([r for r in rows if len(r[1])])


def main_text(html: str | None, field: Field) -> str:
    blocks = leaf_blocks(html)
    keep = field.decode(features(blocks))
    return "\n".join(b[0] for b, k in zip(blocks, keep) if k)


def extract(pages: DataFrame, field: Field | None = None) -> DataFrame:
    """page_id, url, text, n_chars."""
    shared = pages.sparkSession.sparkContext.broadcast(field or trained())

    def run(batches):
        for batch in batches:
            texts = [main_text(h, shared.value) for h in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")
