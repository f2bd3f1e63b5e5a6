"""Fast exact encoding with public vocabularies.

A byte-level BPE never merges across the borders of its pre-tokens, so the ids of a text are the ids of its chunks one
after another, if chunks end at such borders. Chunks repeat often; each worker encodes a chunk once with the tokenizers
library and keeps its ids, as little-endian 32-bit bytes, in a table of bounded size.
"""

from __future__ import annotations

import os
import re
import unicodedata
from array import array

import public_tokenizers
import regex

#: Bytes that a table of chunks may take in a worker; then it starts anew. Longer chunks are not kept.
MOST_BYTES, LONGEST = 36 << 20, 4096
#: Bytes of an entry beside its characters and ids: two objects and a place in the table.
ENTRY = 150
#: White space that is no ASCII white space (fixed values of the Unicode standard, with U+001C-U+001F).
_OTHER_SPACE = re.compile("[\x1c-\x1f\x85\xa0  -     　]")
_ANY_SPACE = re.compile(r"\s")
#: Pre-tokens of word_bpe_49k.json (a fixed value of its file).
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: A space before anything that is not white space: a pre-token begins there.
_BEFORE_SPACE = re.compile(rb"(?<!^)(?= [^\x09-\x0d\x20])")


def _library(path: str):
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_file(path)
    tokenizer.encode_special_tokens = True
    return tokenizer


def _packed(ids: list[int]) -> bytes:
    return array("I", ids).tobytes()


def _byte_letters() -> str:
    """The character that stands for each byte in byte-level vocabularies: itself if it prints, else the next one from 256 on."""
    prints = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = iter(range(256, 512))
    return "".join(chr(x if x in prints else next(rest)) for x in range(256))


class Bounded(dict):
    """A table that forgets everything when its entries take more than ``most`` bytes."""

    def __init__(self, most: int) -> None:
        super().__init__()
        self.most = self.room = most

    def keep(self, key: str | bytes, found: bytes | None) -> bytes | None:
        size = len(key) + len(found or b"")
        if size <= LONGEST:
            self.room -= ENTRY + size
            if self.room < 0:
                self.clear()
                self.room = self.most
            self[key] = found
        return found


class PreTokens(Bounded):
    """Packed ids of a pre-token, from the library's model when first asked for."""

    def __init__(self, model, most: int) -> None:
        super().__init__(most)
        self.model, self.letters = model, _byte_letters()

    def __missing__(self, pre_token: str) -> bytes:
        spelled = pre_token if pre_token.isascii() and pre_token.isalpha() else pre_token.encode().decode("latin-1").translate(self.letters)
        return self.keep(pre_token, array("I", [x.id for x in self.model.tokenize(spelled)]).tobytes())


class Chunks(Bounded):
    """Packed ids of a chunk, found when first asked for; None where its ids depend on what stands around it.

    A chunk of characters below U+0250, whose classes and lower case no Unicode version changes, is cut into pre-tokens
    here (``pattern``, ``fold``) and looked up; others go through the library's own pipeline. ``whole``: white space of
    any kind makes a chunk None (True), only space that isn't ASCII (False), or none does (None).
    """

    def __init__(self, tokenizer, pattern: str, fold=None, whole: bool | None = None, prefix: str = "", known: PreTokens | None = None, most: int = MOST_BYTES) -> None:
        super().__init__(most)
        self.tokenizer, self.fold, self.whole, self.prefix = tokenizer, fold, whole, prefix
        self.cut = regex.compile(pattern).findall
        self.known = PreTokens(tokenizer.model, most) if known is None else known

    def __missing__(self, chunk: bytes) -> bytes | None:
        return self.keep(chunk, self.ids(chunk.decode("utf-8", "replace")))

    def ids(self, text: str) -> bytes | None:
        if self.whole and text.split() != [text] or self.whole is False and _OTHER_SPACE.search(text):
            return None
        if not text.isascii() and max(text) >= "\u0250":
            return _packed(self.tokenizer.encode(self.prefix + text, add_special_tokens=False).ids)
        if self.fold:
            text = self.fold(text)
        known = self.known
        if text.isalpha():
            return known[self.prefix + text]
        if text[-1:] in ("." , ",") and text[:-1].isalpha():
            return known[self.prefix + text[:-1]] + known[text[-1]]
        return b"".join([known[x] for x in self.cut(self.prefix + text)])


class ByteEncoder:
    """Byte-level BPE with leading spaces (``byte_bpe_50k.json``)."""

    def __init__(self, path: str) -> None:
        self.library = _library(path)
        cut = public_tokenizers.PATTERN
        self.later = Chunks(self.library, cut, whole=True, prefix=" ", known=PreTokens(self.library.model, 4 * MOST_BYTES), most=6 * MOST_BYTES)
        self.first = Chunks(self.library, cut, whole=True, known=self.later.known)
        self.rare = Chunks(self.library, cut, whole=False, known=self.later.known, most=MOST_BYTES // 4)
        self.newline = _packed(self.library.encode("\n", add_special_tokens=False).ids)

    def encode(self, texts: list[bytes]) -> list[bytes]:
        """Packed ids of each text."""
        return [self._one(x) for x in texts]

    def _one(self, text: bytes) -> bytes:
        newline, first, later = self.newline, self.first, self.later.__getitem__
        found: list[bytes | None] = []
        for line in text.split(b"\n"):
            parts = line.split(b" ")
            found.append(newline)
            head = parts.pop(0)
            # A line that begins with one space begins with the pre-token of that space and what follows.
            found.append(first[head] if head or not parts or not parts[0] else b"")
            found.extend(map(later, parts))
        found[0] = b""
        try:
            return b"".join(found)
        except TypeError:  # a chunk is None
            return self._slow(text)

    def _slow(self, text: bytes) -> bytes:
        """Texts with runs of white space: cut only before a single space, else the whole text at once."""
        if not text:
            return b""
        try:
            return b"".join(map(self.rare.__getitem__, _BEFORE_SPACE.split(text)))
        except TypeError:
            return _packed(self.library.encode(text.decode("utf-8", "replace"), add_special_tokens=False).ids)


class WordEncoder:
    """BPE with word ends that drops white space (``word_bpe_49k.json``): chunks end at ASCII white space."""

    def __init__(self, path: str) -> None:
        self.chunks = Chunks(_library(path), WORD_PATTERN, fold=lambda x: unicodedata.normalize("NFC", x).lower())

    def encode(self, texts: list[bytes]) -> list[bytes]:
        ids = self.chunks.__getitem__
        return [b"".join(map(ids, x.split())) for x in texts]


class Pieces(Bounded):
    """Packed SentencePiece ids of a word, found when first asked for."""

    def __init__(self, path: str, most: int = MOST_BYTES) -> None:
        import sentencepiece

        super().__init__(most)
        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.byte_ids = [i for i in range(self.model.get_piece_size()) if self.model.is_byte(i)]
        self.encode = self.model.encode

    def __missing__(self, word: bytes) -> bytes:
        return self.keep(word, _packed(self.encode(word.decode("utf-8", "replace"))))


#: The encoder that a worker used last. Workers outlive stages, so another kind of encoder replaces it.
_last: dict[tuple, object] = {}


def _encoder(kind, path: str):
    if (kind, path) not in _last:
        _last.clear()
        _last[kind, path] = kind(path)
    return _last[kind, path]


def byte_encoder(path: str) -> ByteEncoder:
    return _encoder(ByteEncoder, path)


def word_encoder(path: str) -> WordEncoder:
    return _encoder(WordEncoder, path)


def pieces(path: str) -> Pieces:
    return _encoder(Pieces, path)


def vocabulary(name: str) -> str:
    return public_tokenizers.path(name)
