"""BPE ids of whole texts, by the ``tokenizers`` library behind a cache of pre-tokens.

The file's pre-tokenizer cuts a text into pieces that BPE treats one by one, so ids of a piece can be kept.
Texts of common characters are cut here by the same pattern and only unseen pieces go to the library's model;
a text with any other character, or any text where the file has another pre-tokenizer, goes to the library
whole. So does a text that holds the string of an added token, which the library makes one id of.
"""

from __future__ import annotations

import json
import re
from array import array

import numpy as np

#: The characters for which the fast path is taken, by class.
LETTERS = "A-Za-zªµºÀ-ÖØ-öø-ɏ"
NUMBERS = "0-9²³¹¼½¾"
USUAL = re.compile(r"[\t\n\r -~¡-ɏ‐-‧€]*")
PIECES = re.compile(rf"'(?:[stmd]|re|ve|ll)| ?[{LETTERS}]+| ?[{NUMBERS}]+| ?[^\s{LETTERS}{NUMBERS}]+|\s+(?!\S)|\s+")
PLAIN = re.compile(r" ?[!-~]+")
#: The cut and the normalizers of the lower-casing file, and that cut for the usual characters.
WORD_CUT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
WORDS = re.compile(rf"'(?:[stmd]|re|ve|ll)|[{LETTERS}]+|[{NUMBERS}]|[^\s{LETTERS}{NUMBERS}]+")
WORD_NORMALIZERS = ["NFC", "Replace", "Lowercase"]
#: Pieces kept (about 150 bytes each): the first ones met, until so many misses for each piece kept.
MOST_PIECES = 300_000
RENEWAL = 8
#: Bytes that byte-level BPE writes as themselves; the others follow from 256 on, in order.
SELF_BYTES = [*range(33, 127), *range(161, 173), *range(174, 256)]
BYTE_CHARS = {b: b for b in SELF_BYTES} | {b: 256 + i for i, b in enumerate(x for x in range(256) if x not in SELF_BYTES)}


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


_KEPT: dict[str, Encoder] = {}


class Encoder(dict):
    """text -> ids as little-endian unsigned 32-bit bytes."""

    def __init__(self, path: str):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        super().__init__()
        self.misses = 0
        self.library = Tokenizer.from_file(path)
        self.model = self.library.model
        shape = json.loads(self.library.to_str())
        self.added = tuple(x["content"] for x in shape.get("added_tokens") or ())
        cut = shape.get("pre_tokenizer") or {}
        self.by_piece = cut.get("type") == "ByteLevel" and not cut.get("add_prefix_space") and cut.get("use_regex", True) and not shape.get("normalizer") and shape["model"]["type"] == "BPE" and not shape["model"].get("dropout")

        first = (cut.get("pretokenizers") or [{}])[0]
        normal = [x["type"] for x in (shape.get("normalizer") or {}).get("normalizers") or ()]
        self.by_word = first.get("pattern") == {"Regex": WORD_CUT} and first.get("behavior") == "Removed" and first.get("invert") and normal == WORD_NORMALIZERS and not shape["model"].get("dropout")

    def whole(self, text: str) -> bytes:
        return np.array(self.library.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def __missing__(self, piece: str) -> bytes:
        self.misses += 1
        ids = self._piece(piece)
        if len(self) < MOST_PIECES:
            self[piece] = ids
        elif self.misses > RENEWAL * MOST_PIECES:  # the texts have changed: learn anew
            self.clear()
            self.misses = 0
        return ids

    def _piece(self, piece: str) -> bytes:
        written = ("Ġ" + piece[1:] if piece[0] == " " else piece) if PLAIN.fullmatch(piece) else piece.encode().decode("latin-1").translate(BYTE_CHARS)
        return array("I", [t.id for t in self.model.tokenize(written)]).tobytes()

    def encode(self, text: str | None) -> bytes:
        if not text:
            return b""
        if not (self.by_piece or self.by_word) or not USUAL.fullmatch(text) or any(x in text for x in self.added):
            return self.whole(text.encode("utf-8", "replace").decode("utf-8"))
        if self.by_piece:
            return b"".join(map(self.__getitem__, PIECES.findall(text)))
        low = text.lower()
        return b"".join(map(self.__getitem__, WORDS.findall(low))) if USUAL.fullmatch(low) else self.whole(text)


def forget() -> None:
    """Let the worker's encoder go."""
    _KEPT.clear()


def encoder(path: str) -> Encoder:
    """The worker process' encoder for a file: its pieces stay known from task to task."""
    if path not in _KEPT:
        _KEPT.clear()  # one at a time: two would need the memory of two
        _KEPT[path] = Encoder(path)
    return _KEPT[path]
