"""Token ids of whole texts by the tokenizers library, with repeated stretches of text encoded once.

Both public vocabularies pre-split a text so that a single space between two non-space characters always
begins a new piece; what stands between two such spaces can thus be encoded on its own. A stretch is kept
by its text in the worker, which turns most of the work into dictionary lookups. Stretches that begin or
end with other white space are glued to their neighbours first, so that every cut is at such a space.
"""

from __future__ import annotations

import json
import os
from collections.abc import Callable

import numpy as np
import regex

from .common import Bounded, begin

#: Bytes of a cache generation of words and of pieces in a Python worker, and what an entry takes besides its texts; two generations are kept.
WORD_BYTES, PIECE_BYTES, ENTRY_BYTES = 72 << 20, 24 << 20, 120
#: Code points up to here have the same classes in every Unicode version that the libraries may carry.
PLAIN = regex.compile(r"[\n\x20-\x7e¡-ɏ]*")
#: How the two vocabularies cut a text into pieces.
BYTE_PIECES = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+")
MARKS = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
WORD_RULE = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
WORD_PIECES = regex.compile(WORD_RULE)
_encoders: dict[str, Encoder] = {}


class Generations(Bounded):
    """A bounded cache: a full generation becomes the old one; what is used again moves to the new one."""

    def __init__(self, make: Callable[[str], bytes | None], most: int, quick: bool):
        super().__init__(most, quick)
        self.make, self.old = make, {}

    def drop(self) -> None:
        super().drop()
        self.old = {}

    def __missing__(self, key: str) -> bytes | None:
        if (v := self.old.get(key)) is None:
            v = self.make(key)
        if self.held >= self.most:
            self.old, self.held = dict(self), 0
            self.clear()
        self.held += ENTRY_BYTES + len(key) + len(v or b"")  # measured: 150 bytes a word
        self[key] = v
        return v


def style(config: dict) -> str | None:
    """Which of the two known ways of cutting a text a vocabulary file states: "byte", "word" or neither."""
    before, cut = config["normalizer"] or {}, config["pre_tokenizer"] or {}
    if config["truncation"] or config["post_processor"] or any(t["normalized"] or t["lstrip"] or t["rstrip"] or t["single_word"] for t in config["added_tokens"]):
        return None
    if not before and (cut.get("type"), cut.get("add_prefix_space"), cut.get("use_regex")) == ("ByteLevel", False, True):
        return "byte"
    steps, cuts = [(n["type"], n.get("pattern"), n.get("content")) for n in before.get("normalizers", [])], cut.get("pretokenizers", [])
    if steps == [("NFC", None, None), ("Replace", {"Regex": r"\s+"}, " "), ("Lowercase", None, None)] and [c["type"] for c in cuts] == ["Split", "ByteLevel"]:
        split, level = cuts
        if (split["pattern"], split["behavior"], split["invert"]) == ({"Regex": WORD_RULE}, "Removed", True) and not level["add_prefix_space"] and not level["use_regex"]:
            return "word"
    return None


class Encoder:
    """Ids of texts as uint32 arrays, as ``encode(text, add_special_tokens=False)`` gives them."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        os.environ["RAYON_NUM_THREADS"] = "1"
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.style = style(json.loads(self.tokenizer.to_str()))
        self.lower = self.style == "word"
        self.pieces = (WORD_PIECES if self.lower else BYTE_PIECES).findall
        # the byte-level alphabet, as the library itself maps single bytes
        seen = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        self.alphabet = {b: seen.pre_tokenize_str(chr(b))[0][0] for b in range(128)} | {
            b: s[1] for b in range(128, 192) if (s := seen.pre_tokenize_str(bytes([0xC3, b]).decode())[0][0])} | {
            b: s[0] for b in range(0xC3, 0xCA) if (s := seen.pre_tokenize_str(bytes([b, 0x81]).decode())[0][0])} | {0xC2: seen.pre_tokenize_str("¡")[0][0][0]}
        self.space, self.tokenize = self.alphabet[32], self.model.tokenize
        self.four = [i.to_bytes(4, "little") for i in range(self.tokenizer.get_vocab_size())]
        self.word, self.piece = Generations(self._word, WORD_BYTES, False), Generations(self._piece, PIECE_BYTES, False)

    def _piece(self, piece: str) -> bytes:
        raw = piece.replace(" ", self.space) if piece.isascii() and piece.isprintable() else piece.encode().decode("latin-1").translate(self.alphabet)
        four = self.four
        return b"".join([four[t.id] for t in self.tokenize(raw)])

    def _stretch(self, text: str) -> bytes:
        if not PLAIN.fullmatch(text):
            return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, np.uint32).tobytes()
        return b"".join(map(self.piece.__getitem__, self.pieces(text.lower() if self.lower else text)))

    def _word(self, word: str) -> bytes | None:
        """Ids of " word"; None if white space at an end makes the cut depend on what stands beside it."""
        if word == "":
            return b"" if self.lower else None
        if not self.lower and (word[0].isspace() or word[-1].isspace()):
            return None
        if not word.isascii() and max(word) > "\u024f":
            return self._stretch(" " + word)
        low, lead = (word.lower(), "") if self.lower else (word, " ")
        letters = low.rstrip(MARKS)
        if letters.isalpha():  # letters, then marks if any: one piece each
            if len(letters) == len(low):
                return self._piece(lead + low)
            return (self.word[letters] if self.lower else self.piece[lead + letters]) + self.piece[low[len(letters) :]]
        return self._stretch(" " + word)

    def _words(self, text: str) -> list[str]:
        """What stands between spaces and line ends, which are in no piece of this style; in lower case where that depends on no neighbours."""
        plain = text.isascii() or PLAIN.fullmatch(text)
        return (text.lower() if plain else text).replace("\n", " ").split(" ")

    def _slowly(self, text: str) -> bytes:
        """Stretches are glued where white space stands beside a single space."""
        first, *rest = text.split(" ")
        out = [first]
        for r in rest:
            if r == "" or r[0].isspace() or out[-1] == "" or out[-1][-1].isspace():
                out[-1] += " " + r
            else:
                out.append(" " + r)
        return b"".join(map(self._stretch, out))

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        if self.style is None:  # a file that cuts texts otherwise: the library alone
            return [np.array(self.tokenizer.encode(t, add_special_tokens=False).ids, np.uint32) for t in texts]
        get, out = self.word.__getitem__, []
        for t in texts:
            if any(s in t for s in self.special):  # their strings are cut out before anything else
                out.append(np.array(self.tokenizer.encode(t, add_special_tokens=False).ids, np.uint32))
                continue
            if self.lower:
                out.append(np.frombuffer(b"".join(map(get, self._words(t))), np.uint32))
                continue
            first, *rest = t.split(" ")
            try:
                if first == "" or first[-1].isspace():
                    raise TypeError
                ids = self._stretch(first) + b"".join(map(get, rest))
            except TypeError:
                ids = self._slowly(t)
            out.append(np.frombuffer(ids, np.uint32))
        return out


def encoder(path: str) -> Encoder:
    """The worker's encoder of a vocabulary file."""
    begin()
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)
