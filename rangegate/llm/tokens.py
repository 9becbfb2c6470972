"""Token ids of whole texts by a public lower-case word-BPE file, faster than text by text.

The file's pre-tokeniser cuts a normalised text into pieces that are encoded one by one, so the ids of a piece do not
depend on its neighbours. Texts of Latin letters, digits, ASCII marks and plain spaces are cut here by the same pattern
and each distinct piece is encoded once and kept; a text with any other character goes to the tokenizer whole.
"""

from __future__ import annotations

import re

import numpy as np

#: The pre-tokeniser's pattern for the characters let through by PLAIN (fixed value).
PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zßà-öø-ÿœ]+|[0-9]|[^\sa-zßà-öø-ÿœ0-9]+")
#: Characters for which lower-casing, composition and classes agree in both places (fixed value).
PLAIN = re.compile("[\t\n\r -~ßÀ-ÖØ-öø-ÿŒœ¡¿«»–—‘’“”…€]*")
END_ID = 1


class WordBpe:
    """Encoder of one worker; ``limit`` bounds the pieces that are kept."""

    def __init__(self, path: str, limit: int = 400_000):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.limit = limit
        self.known: dict[str, bytes] = {}

    def _learn(self, pieces: set[str]) -> None:
        """Makes all of ``pieces`` known; beyond the limit older ones go first, those asked for never do."""
        new = list(pieces.difference(self.known))
        if len(self.known) + len(new) > self.limit:
            self.known.clear()
            new = list(pieces)
        for at in range(0, len(new), 2000):
            part = new[at : at + 2000]
            e = self.tokenizer.encode(" ".join(part), add_special_tokens=False)  # a space parts the pieces
            ids, ends = np.array(e.ids, dtype="<u4").tobytes(), (np.cumsum(np.bincount(e.word_ids, minlength=len(part))) * 4).tolist()
            for piece, a, b in zip(part, [0, *ends], ends, strict=False):
                self.known[piece] = ids[a:b]

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers; a null text has none."""
        cut = [PIECES.findall(t.lower()) if t and PLAIN.fullmatch(t) else t for t in texts]
        self._learn({p for c in cut if isinstance(c, list) for p in c})
        known = self.known
        return [b"".join([known[p] for p in c]) if isinstance(c, list) else self._whole(c) for c in cut]

    def _whole(self, text: str | None) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes() if text else b""


_ENCODERS: dict[str, WordBpe] = {}


def encoder(path: str) -> WordBpe:
    """This process's encoder; its pieces outlive a task."""
    if path not in _ENCODERS:
        _ENCODERS[path] = WordBpe(path)
    return _ENCODERS[path]


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")
