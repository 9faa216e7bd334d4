"""Token ids by the public tokenizers, quickly.

Both BPE vocabularies split a text into pieces before they merge. No piece spans a space or line break that stands between two
other characters, nor the place between a letter or digit and a comma or full stop. So a text is cut there, each distinct chunk
is encoded once by the tokenizers library, and its ids are kept. Texts where such places can't be told apart by their
neighbours alone are cut at single spaces only. A chunk of letters is one piece, so the vocabulary's model takes it
directly; all others go through the whole tokenizer."""

from __future__ import annotations

import os
import re
from array import array

_ODD = re.compile(r"\s\s|[\W_][.,]|\0")
_SAFE = re.compile(r"(?<=\S)(?= \S)")
_kept: dict[str, Encoder] = {}
CACHE_BYTES = 40 << 20
#: The first 256 characters by kind, for a search without regular expressions: space, comma or stop, other sign, letter or digit.
_KIND = bytes(32 if chr(c).isspace() else 46 if c in b".," else 97 if chr(c).isalnum() else 33 for c in range(256))


def _byte_letters() -> dict[int, str]:
    """The printable character that stands for each byte in byte-level vocabularies: itself if printable, else the next free one
    from 256 on."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in printable]
    return {b: chr(256 + k) for k, b in enumerate(rest)}


_LETTERS = _byte_letters()


class Encoder(dict):
    """chunk -> ids as little-endian unsigned 32-bit integers, learned as asked; called with texts, it gives theirs.

    Chunks are kept in two generations of about ``room`` bytes each; when the younger is full, the older goes. The strings of the vocabulary's
    added tokens become those tokens, as in the library's plain call, or with ``added_as_text`` ordinary text; such texts
    are left to the library whole."""

    LONGEST, ENTRY = 256, 200

    def __init__(self, path: str, added_as_text: bool = False):
        super().__init__()
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = added_as_text
        normalizer = self.tokenizer.normalizer
        self.added = [t.content.lower() for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.lowers = normalizer is not None and normalizer.normalize_str("A") == "a"
        self.changes = normalizer is not None
        self.space = "" if self.tokenizer.encode(" a", add_special_tokens=False).tokens == self.tokenizer.encode("a", add_special_tokens=False).tokens else _LETTERS[32]
        self.pieces = self.tokenizer.model.tokenize
        self.older: dict[str, bytes] = {}
        self.held, self.room = 0, CACHE_BYTES

    @staticmethod
    def chunks(text: str) -> list[str]:
        """Pieces that can be encoded apart; joined they are the text."""
        try:
            kinds = text.encode("latin-1").translate(_KIND)
            odd = b"  " in kinds or b" ." in kinds or b"!." in kinds or b".." in kinds or "\0" in text
        except UnicodeEncodeError:
            odd = _ODD.search(text)
        if odd:
            return _SAFE.split(text)
        return text.replace(" ", "\0 ").replace(",", "\0,").replace(".", "\0.").replace("\n", "\0\n\0").split("\0")

    def __missing__(self, chunk: str) -> bytes:
        found = self.older.get(chunk)
        if found is None:
            lead, letters = (self.space, chunk[1:]) if chunk[:1] == " " else ("", chunk)
            if letters.isalpha() and letters.isascii():
                ids = [t.id for t in self.pieces(lead + letters)]
            elif letters.isalpha() and not self.changes:
                ids = [t.id for t in self.pieces(lead + letters.encode().decode("latin-1").translate(_LETTERS))]
            else:
                ids = self.tokenizer.encode(chunk, add_special_tokens=False).ids
            found = array("I", ids).tobytes()
        if len(chunk) <= self.LONGEST:
            self.held += self.ENTRY + len(chunk) + len(found)
            if self.held > self.room:
                self.older = dict(self)
                self.clear()
                self.held = 0
            self[chunk] = found
        return found

    def _encode(self, text: str) -> bytes:
        low = text.lower()
        if any(t in low for t in self.added):
            return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()
        if self.lowers:  # what the vocabulary does anyway, so that capitals make no further chunks
            text = text.encode().lower().decode()
        return b"".join(map(self.__getitem__, self.chunks(text)))

    def __call__(self, batch: list[str | None]) -> list[bytes]:
        return [self._encode(t) if t else b"" for t in batch]


def encoder(path: str, room: int = CACHE_BYTES) -> Encoder:
    """One for each worker process and vocabulary."""
    if path not in _kept:
        _kept[path] = Encoder(path)
    _kept[path].room = room
    return _kept[path]
