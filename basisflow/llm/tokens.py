"""Whole-text encoding with a public tokenizer file, through a cache of words.

The word tokenizer normalises and splits text so that ids never depend on
anything across ASCII white space: text is cut there, each distinct piece is
encoded once by the tokenizers library, and ids are put together again.
"""

from __future__ import annotations

import struct
import unicodedata
from itertools import chain

import numpy as np

from .common import KEPT

#: Pieces in one generation of a Python worker's cache, and pieces of text encoded together.
CACHE_PIECES, GROUP_PIECES = 300_000, 100_000
#: Marks between which and a letter the tokenizer always cuts (none that ends an added token).
MARKS = b".,;:!?|&%$#*+-=_~^@/()[]{}"
#: Packers made beforehand, by number of ids.
PACKERS = 64
#: Last character for which letters and their lower case are settled in every version of Unicode.
LATIN = "\u024f"
DEFAULT = "word_bpe_49k.json"


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(DEFAULT)


def _byte_letters() -> dict[int, int]:
    """The public byte-level alphabet: printable Latin-1 stands for itself, other bytes follow from U+0100."""
    printable = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    rest = [b for b in range(256) if b not in printable]
    return {b: b for b in printable} | {b: 0x100 + i for i, b in enumerate(rest)}


class WordEncoder:
    """Ids of texts, through two generations of cached pieces: what the younger one lacks moves up from the older.

    A-Z are lowered first, as the tokenizer does after composing characters; a piece that ends in
    an ASCII letter and then marks is two: the tokenizer always cuts between letters and these marks.
    Strings of added tokens count as the tokenizer has it, in their own case only: pieces that may hold one go to it as they are.
    """

    def __init__(self, path: str | None = None, cache: int = CACHE_PIECES):
        from tokenizers import Tokenizer

        self._tokenizer = Tokenizer.from_file(path or default_path())
        self._special = [t.content.encode() for t in self._tokenizer.get_added_tokens_decoder().values()]
        self.dtype = "<u2" if self._tokenizer.get_vocab_size() <= 1 << 16 else "<u4"
        self._bytes = _byte_letters() if path is None or path.endswith(DEFAULT) else None
        self._young: dict[bytes, bytes] = {}
        self._old: dict[bytes, bytes] = {}
        self._most = cache

    def _learn(self, pieces: set[bytes]):
        """Puts the pieces, of which the younger generation lacks some, into it."""
        if len(self._young) + len(pieces) > self._most:
            self._old, self._young = self._young, {}
        old, young = self._old, self._young
        packers = [struct.Struct(f"<{n}{'H' if self.dtype == '<u2' else 'I'}").pack for n in range(PACKERS)]
        tokenize, plain = self._tokenizer.model.tokenize, self._plain
        later: list[tuple[bytes, bytes, bytes]] = []
        lacking: dict[bytes, None] = {}

        def pack(ids):
            n = len(ids)
            return packers[n](*ids) if n < PACKERS else np.array(ids, self.dtype).tobytes()

        def known(part):
            """Ids of a part, or None where it is left to the tokenizer."""
            if (packed := young.get(part)) is None:
                if (packed := old.get(part)) is None:
                    if (text := plain(part)) is None:
                        lacking[part] = None
                        return None
                    packed = pack([t.id for t in tokenize(text)])
                young[part] = packed
            return packed

        for piece in pieces:
            if piece in young:
                continue
            if (packed := old.get(piece)) is not None:
                young[piece] = packed
                continue
            stem, marks = self._cut(piece)
            if not marks:
                known(piece)
                continue
            first, last = known(stem), known(marks)
            if first is None or last is None:
                later.append((piece, stem, marks))
            else:
                young[piece] = first + last
        some = list(lacking)
        for at in range(0, len(some), 50_000):
            part = some[at : at + 50_000]
            found = self._tokenizer.encode_batch_fast([p.decode() for p in part], add_special_tokens=False)
            young.update(zip(part, [pack(e.ids) for e in found], strict=True))
        for piece, stem, marks in later:
            young[piece] = young[stem] + young[marks]

    def forget_older(self):
        self._old = {}

    @staticmethod
    def _cut(piece: bytes) -> tuple[bytes, bytes]:
        """A piece as its part up to an ASCII letter and the marks after it; one that does not end so stays whole."""
        stem = piece.rstrip(MARKS)
        return (stem, piece[len(stem) :]) if stem[-1:].isalpha() else (piece, b"")

    def _plain(self, piece: bytes) -> str | None:
        """A piece of Latin letters as the tokenizer's model gets it, or None: such pieces are one word, whatever stands around them."""
        if piece.isalpha():  # of bytes: ASCII letters only
            return piece.decode() if self._bytes else None
        text = piece.decode()
        if not self._bytes or not text.isalpha() or max(text) > LATIN or "\u0130" in text or unicodedata.normalize("NFC", text) != text:
            return None
        return text.lower().encode().decode("latin-1").translate(self._bytes)

    def packed(self, texts: list[bytes | None]):
        """Little-endian ids (of ``dtype``) of each UTF-8 text, some texts at a time."""
        group: list[list[bytes]] = []
        size = 0
        for text in texts:
            group.append(self._pieces(text or b""))
            size += len(group[-1])
            if size >= GROUP_PIECES:
                yield from self._group(group)
                group, size = [], 0
        yield from self._group(group)

    def _pieces(self, text: bytes) -> list[bytes]:
        low = text.lower()
        some = [t for t in map(bytes.lower, self._special) if t in low]
        if not some:
            return low.split()
        return [p if any(t in p.lower() for t in some) else p.lower() for p in text.split()]

    def _group(self, group):
        pieces = list(chain.from_iterable(group))
        found = list(map(self._young.get, pieces))
        gaps = [i for i, ids in enumerate(found) if ids is None]
        if gaps:
            self._learn({pieces[i] for i in gaps})
            take = self._young.get
            for i in gaps:
                found[i] = take(pieces[i])
        at = 0
        for own in group:
            yield b"".join(found[at : at + len(own)])
            at += len(own)


#: Freed when a worker turns to a task of another kind (``common.tidied``).
_ENCODERS: dict[tuple[str | None, int], WordEncoder] = KEPT.setdefault("encoders", {})


def encoder(path: str | None = None, cache: int = CACHE_PIECES) -> WordEncoder:
    """One encoder per worker process, file and size of cache."""
    if (path, cache) not in _ENCODERS:
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        _ENCODERS[path, cache] = WordEncoder(path, cache)
    return _ENCODERS[path, cache]
