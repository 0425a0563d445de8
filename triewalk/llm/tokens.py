"""Token ids of the public word BPE by the tokenizers library, with a cache of words.

Text of characters that are, and whose lower case is, below U+0250 is normalised and cut into words here, by the same rules as
the tokenizer file states, and each new word goes through the library's BPE model once; a two-generation cache of bounded
size keeps frequent words. Any other text, any that holds a special token's string, and every text under a tokenizer
file that states other rules goes through the library whole.
"""

from __future__ import annotations

import json
import re
import unicodedata
from array import array

END_ID = 1
#: Words of one generation; two are kept, about 120 MB a worker at most.
CACHE_WORDS = 300_000
_LIMIT = 0x250
#: The rules of a tokenizer file that the cutter of words follows.
NORMALIZER = {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]}
PRE_TOKENIZER = {
    "type": "Sequence",
    "pretokenizers": [
        {"type": "Split", "pattern": {"Regex": "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"}, "behavior": "Removed", "invert": True},
        {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
    ],
}


def _classes() -> tuple[str, str, str]:
    letters = "".join(re.escape(chr(c)) for c in range(_LIMIT) if unicodedata.category(chr(c))[0] == "L")
    numbers = "".join(re.escape(chr(c)) for c in range(_LIMIT) if unicodedata.category(chr(c))[0] == "N")
    spaces = "".join(re.escape(chr(c)) for c in range(_LIMIT) if re.match(r"\s", chr(c)) and c not in (0x1C, 0x1D, 0x1E, 0x1F))
    return letters, numbers, spaces


def _leaving() -> str:
    """Characters below the limit whose lower case is not one character below it."""
    return "".join(re.escape(c) for c in map(chr, range(_LIMIT)) if len(c.lower()) > 1 or ord(c.lower()) >= _LIMIT)


def same_rules(path: str) -> bool:
    """Whether a tokenizer file states the rules that the cutter follows."""
    with open(path, encoding="utf-8") as f:
        stated = json.load(f)
    plain = all(not any(t[k] for k in ("single_word", "lstrip", "rstrip", "normalized")) for t in stated["added_tokens"])
    return plain and stated["normalizer"] == NORMALIZER and stated["pre_tokenizer"] == PRE_TOKENIZER and stated["model"]["type"] == "BPE" and not stated["truncation"]


def _byte_chars() -> dict[int, str]:
    """The printable character by which byte-level BPE writes each byte: itself if printable, else the next free one from U+0100."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    out, nxt = {b: chr(b) for b in plain}, 0x100
    for b in range(0x100):
        if b not in out:
            out[b] = chr(nxt)
            nxt += 1
    return out


class WordEncoder(dict):
    """Maps a word to the little-endian unsigned 32-bit ids of its tokens; encode() does whole texts."""

    def __init__(self, path: str):
        super().__init__()
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        letters, numbers, spaces = _classes()
        self.words = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{letters}]+|[{numbers}]|[^{spaces}{letters}{numbers}]+").findall
        special = [re.escape(t.content) for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.odd = re.compile("|".join([rf"[^\x00-\x1b\x20-{chr(_LIMIT - 1)}]", f"[{_leaving()}]", *special])).search if same_rules(path) else lambda text: True
        self.bytes = _byte_chars()
        self.old: dict[str, bytes] = {}

    def __missing__(self, word: str) -> bytes:
        ids = self.old.get(word)
        if ids is None:
            ids = array("I", [t.id for t in self.model.tokenize(word if word.isascii() and word.isprintable() else word.encode().decode("latin-1").translate(self.bytes))]).tobytes()
        if len(self) >= CACHE_WORDS:
            self.old = dict(self)
            self.clear()
        self[word] = ids
        return ids

    def encode(self, text: str | None) -> bytes:
        """Ids of a whole text (null: empty) with the end id, as bytes."""
        if not text:
            return b"\x01\x00\x00\x00"
        if self.odd(text):
            return array("I", [*self.tokenizer.encode(text, add_special_tokens=False).ids, END_ID]).tobytes()
        if not text.isascii():
            text = unicodedata.normalize("NFC", text)
        return b"".join(map(self.__getitem__, self.words(text.lower()))) + b"\x01\x00\x00\x00"


_encoders: dict[str, WordEncoder] = {}


def encoder(path: str) -> WordEncoder:
    """One encoder a worker process and tokenizer file."""
    if path not in _encoders:
        _encoders[path] = WordEncoder(path)
    return _encoders[path]
