"""Token ids of a public byte-level BPE vocabulary, by the tokenizers library's plain call without added tokens.

Words come back all the time, so ids are kept by word. A text is cut before a space
that stands between two characters which are no white space: the vocabulary's
pattern begins a piece at every such space and never reaches over it, and special
tokens hold no space, so the parts' ids one after another are the text's ids. A part
of Latin letters alone is one piece of that pattern, and a mark after them another:
the library's model reads such pieces without the rest of its call. Words are kept
for themselves, so a mark or a line break beside them makes no new word.
"""

from __future__ import annotations

import os
import re
from array import array

import numpy as np

#: Words whose ids are kept, and the longest such word. The stores are emptied when they are full.
KEPT_WORDS, KEPT_LENGTH = 800_000, 64
_NO_CUT = re.compile(r"\s | \s")
_MARKS, _LATIN_END = ".,;:!?", "\u0250"


def _byte_letters() -> dict[int, str]:
    """The public byte-level alphabet: printable bytes stand for themselves, the others for the characters from 256 on."""
    printable = {*range(33, 127), *range(161, 173), *range(174, 256)}
    others = [b for b in range(256) if b not in printable]
    return {b: chr(256 + i) for i, b in enumerate(others)}


def _letters(word: str) -> bool:
    return word.isalpha() and (word.isascii() or max(word) < _LATIN_END)


class Encoder:
    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self._tokenizer, self._kept, self._bytes = Tokenizer.from_file(path), {}, _byte_letters()
        self._begun: dict[str, bytes] = {}  # words that begin a line
        self._model = self._tokenizer.model
        self._marks = dict(zip(_MARKS + "\n", self._read(list(_MARKS + "\n")), strict=True))

    def _word(self, letters: str, before: str = " ") -> bytes:
        """The ids of letters with what stands before them: a space or nothing."""
        piece = self._bytes[32] + letters if before else letters
        if not letters.isascii():
            piece = f"{before}{letters}".encode().decode("latin-1").translate(self._bytes)
        return array("I", [t.id for t in self._model.tokenize(piece)]).tobytes()

    def _line(self, part: str, before: str) -> bytes | None:
        """The ids of a word, or of a word and a mark; None of others."""
        store = self._kept if before else self._begun
        ids = store.get(part)
        if ids is not None:
            return ids
        if _letters(part):
            ids = self._word(part, before)
        elif part and part[-1] in _MARKS and _letters(part[:-1]):
            ids = self._line(part[:-1], before) + self._marks[part[-1]]
        if ids is not None and len(part) <= KEPT_LENGTH:
            store[part] = ids
        return ids

    def _parts(self, new: list[str]) -> dict[str, bytes]:
        """The ids of parts, each after a space. One line break between two words is a piece of its own."""
        read, rest = {}, []
        for p in new:
            if "\n" not in p:
                ids = self._line(p, " ")
                if ids is None:
                    rest.append(p)
                else:
                    read[p] = ids
                continue
            first, *lines = p.split("\n")
            ids = [self._line(first, " "), *(self._line(x, "") for x in lines)]
            if None in ids:
                rest.append(p)
            else:
                read[p] = self._marks["\n"].join(ids)
        read.update(zip(rest, self._read([f" {p}" for p in rest]), strict=True))
        return read

    def _read(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self._tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def ids(self, text: str) -> np.ndarray:
        first, *parts = text.split(" ")
        if not all(parts) or _NO_CUT.search(text):  # white space beside white space has no cut in it
            first, *parts = _safe_parts([first, *parts])
        found = [self._line(first, "") or self._read([first])[0], *map(self._kept.get, parts)]
        try:
            return np.frombuffer(b"".join(found), "<u4")
        except TypeError:  # a part that is not kept
            new = {p for p, ids in zip(parts, found[1:], strict=True) if ids is None}
        read = self._parts(list(new))
        found[1:] = [read[p] if ids is None else ids for p, ids in zip(parts, found[1:], strict=True)]
        if len(self._kept) + len(self._begun) > KEPT_WORDS:
            self._kept.clear()
            self._begun.clear()
        self._kept.update((p, ids) for p, ids in read.items() if len(p) <= KEPT_LENGTH and "\n" not in p)
        return np.frombuffer(b"".join(found), "<u4")


def _safe_parts(parts: list[str]) -> list[str]:
    """The parts again, those joined that have white space on either side of their border."""
    out, run, open_end = [], [], False
    for p in parts:
        if run and not open_end and p and not p[0].isspace():
            out.append(" ".join(run))
            run = []
        run.append(p)
        open_end = not p or p[-1].isspace()
    out.append(" ".join(run))
    return out


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")
