"""Encoding whole texts with a given tokenizer file, with a bounded memory of the pieces seen before.

Byte-pair merging never crosses the borders that a tokenizer's own splitting rule draws. Both kinds of tokenizers used
here always draw one at a single space between two other characters that are not white space (the byte-level kind gives
the space to the next piece, the word-end kind drops it), around a single line feed between such characters, and between
letters and the usual closing signs. So a text is cut at spaces, every distinct piece is composed of its parts once, and
remembered. Parts that are Latin letters only are one word to the splitting rule, so they go straight to the library's
merging model, without the library's normalising and splitting. Texts in which white space stands together are cut so that it stays whole. Texts that hold a special string of the tokenizer, and texts for other tokenizers, are encoded whole.
"""

from __future__ import annotations

import os
import re

import numpy as np

_INNER_SPACE = re.compile(r"(?<=\S) (?=\S)")
#: Words of Latin letters, which every version of the Unicode tables takes for letters and composes and lower-cases alike.
_LATIN = re.compile("[A-Za-zÀ-ÖØ-öø-ɏ]+").fullmatch
_CLOSING = ".,;:!?#*%&$|)"
#: Pieces remembered in each of two generations; older ones are forgotten, which only costs time.
REMEMBERED = 250_000


def vocabulary(name: str) -> str:
    """The place of a public tokenizer file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def _apart(text: str) -> bool:
    """Whether white space stands neither together nor at an end: there is one less of it than words."""
    words = text.split()
    return len(text) == sum(map(len, words)) + len(words) - 1


class _Shown(dict):
    """For str.translate: how the models show the bytes of a character, asked of the library once a character."""

    def __init__(self, splitter):
        self._splitter = splitter

    def __missing__(self, code: int) -> str:
        self[code] = self._splitter.pre_tokenize_str(chr(code))[0][0]
        return self[code]


class _Pieces(dict):
    """Ids of pieces; a new one is taken from the older generation or learned."""

    def __init__(self, learn, old: dict[str, bytes]):
        self._learn, self._old = learn, old

    def __missing__(self, piece: str) -> bytes:
        ids = self._old.get(piece)
        if ids is None:
            ids = self._learn(piece)
        self[piece] = ids
        return ids


class Encoder:
    """encode(texts) gives the ids of each text as little-endian unsigned 32-bit integers, in bytes."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer, pre_tokenizers

        self._tokenizer = Tokenizer.from_file(path)
        tokens = self._tokenizer.get_added_tokens_decoder().values()
        self._special = [t.content for t in tokens]
        #: The largest id.
        self.most = max(self._tokenizer.get_vocab(with_added_tokens=True).values(), default=0)
        end = self._tokenizer.model.end_of_word_suffix
        splits, normal = str(self._tokenizer.pre_tokenizer), str(self._tokenizer.normalizer)
        known = not self._tokenizer.model.dropout and not any(t.normalized or t.lstrip or t.rstrip or t.single_word for t in tokens)
        self._words = known and bool(end) and "Lowercase" in normal and "Removed" in splits and "ByteLevel(" in splits
        self._bytes = known and not end and normal == "None" and splits.startswith("ByteLevel(") and "add_prefix_space=False" in splits and "use_regex=True" in splits
        self._model = self._tokenizer.model
        self._raw = [i.to_bytes(4, "little") for i in range(self._tokenizer.get_vocab_size() + 1)]
        self._shown = _Shown(pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False))
        self._signs: dict[str, bytes] = {"": b""}
        self._lead = "" if self._words else self._shown[32]
        self._young = _Pieces(self._learn, {})

    def _plain(self, texts: list[str]) -> list[bytes]:
        encode = getattr(self._tokenizer, "encode_batch_fast", self._tokenizer.encode_batch)
        return [np.array(e.ids, "<u4").tobytes() for e in encode(texts, add_special_tokens=False)]

    def _letters(self, word: str, lead: str) -> bytes:
        """The ids of one word as the model sees it: its letters shown as bytes, lead for a space before it."""
        raw = self._raw
        return b"".join([raw[t.id] for t in self._model.tokenize(lead + (word if word.isascii() else word.translate(self._shown)))])

    def _closing(self, signs: str) -> bytes:
        if signs not in self._signs:
            if len(self._signs) > REMEMBERED:
                self._signs = {"": b""}
            self._signs[signs] = self._plain([signs])[0]
        return self._signs[signs]

    def _lines(self, piece: str) -> list[str] | None:
        """The pieces that a piece with line feeds is composed of; None where white space stands together in it."""
        lines = piece.split("\n")
        if self._words:  # white space is only a border there
            return lines
        if not all(lines) or any(x[0].isspace() or x[-1].isspace() for x in lines):
            return None
        return [lines[0], *("\n" + x for x in lines[1:])]

    def _learn(self, piece: str) -> bytes:
        """The ids of a piece, standing after a space or, in the byte-level kind, after the line feed that it begins with."""
        feed = self._bytes and piece[0] == "\n" if piece else False
        if "\n" in piece[feed:]:
            parts = self._lines(piece)
            return b"".join([self._young[x] for x in parts]) if parts else self._plain([piece if feed else " " + piece])[0]
        whole = piece[1:] if feed else piece
        stem = whole.rstrip(_CLOSING)
        signs = whole[len(stem) :]
        if self._words:
            stem = stem.lower()
        if not _LATIN(stem):
            return self._plain([piece if feed else " " + piece])[0]
        if feed:
            return self._closing("\n") + self._letters(stem, "") + self._closing(signs)
        if stem == piece:
            return self._letters(stem, self._lead)
        return self._young[stem] + self._closing(signs)

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of whole texts, as the library's encode(text, add_special_tokens=False) gives them."""
        if not (self._words or self._bytes):
            return self._plain(texts)
        whole = [i for i, t in enumerate(texts) if any(x in t for x in self._special)]
        if not whole:
            return self._pieced(texts)
        held = dict(zip(whole, self._plain([texts[i] for i in whole]), strict=True))
        rest = iter(self._pieced([t for i, t in enumerate(texts) if i not in held]))
        return [held[i] if i in held else next(rest) for i in range(len(texts))]

    def _pieced(self, texts: list[str]) -> list[bytes]:
        cut = [t.split(" ") if self._words or _apart(t) else _INNER_SPACE.split(t) for t in texts]
        firsts: list[bytes] = []
        if self._bytes:  # the first piece stands after no space
            firsts = self._plain([pieces[0] for pieces in cut])
            cut = [pieces[1:] for pieces in cut]
        if len(self._young) > REMEMBERED:
            self._young = _Pieces(self._learn, dict(self._young))
        get = self._young.__getitem__
        if firsts:
            return [first + b"".join(map(get, pieces)) for first, pieces in zip(firsts, cut, strict=True)]
        return [b"".join(map(get, pieces)) for pieces in cut]


_ENCODERS: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """The process's encoder for a tokenizer file."""
    if path not in _ENCODERS:
        _ENCODERS[path] = Encoder(path)
    return _ENCODERS[path]
