"""A SentencePiece vocabulary as a unigram model.

The file's merge order is turned into log-probabilities by rank (a Zipf law
over the ordinary pieces).  A character that is no piece falls back to its
bytes, each at the price of the rarest piece.

A text is split in one of two ways, and no piece crosses a split.  ``units_of``
keeps all of it, as the library does: a mark in front, a mark for each blank,
newlines and tabs as units of their own.  ``words_of`` keeps the words only:
they are separated by ASCII blanks and get the mark in front.
"""

from __future__ import annotations

import re
from functools import lru_cache

import numpy as np

MARK = "▁"
UNIT = re.compile(r"[\n\t]+|▁*[^▁\n\t]+|▁+")


class Pieces:
    def __init__(self, path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        size = sp.get_piece_size()
        self.text = [sp.id_to_piece(i) for i in range(size)]
        special = [i for i in range(size) if sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i)]
        self.bytes = [sp.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
        self.byte_of = {i: b for b, i in enumerate(self.bytes)}
        out = set(special) | {i for i in self.bytes if sp.is_byte(i)}
        plain = [i for i in range(size) if i not in out]
        lp = -np.log(np.arange(1, len(plain) + 1)) - np.log((1.0 / np.arange(1, len(plain) + 1)).sum())
        self.logp = {self.text[i]: float(x) for i, x in zip(plain, lp)}
        self.id = {self.text[i]: i for i in plain}
        self.floor = float(lp[-1])
        self.longest = max(map(len, self.logp))
        if any(UNIT.match(t).end() < len(t) for t in self.logp):
            raise ValueError("a piece crosses units")

    def ids_of(self, piece: str) -> list[int]:
        return [self.id[piece]] if piece in self.id else [self.bytes[b] for b in piece.encode("utf-8", "surrogatepass")]

    def decode(self, ids) -> str:
        """The text of a piece sequence; of words, joined by single blanks."""
        back = self.byte_of
        if not any(map(back.__contains__, ids)):
            return "".join(map(self.text.__getitem__, ids)).replace(MARK, " ").removeprefix(" ")
        out, run = [], bytearray()
        for i in ids:
            if i in back:
                run.append(back[i])
                continue
            if run:
                out.append(run.decode("utf-8", "surrogatepass"))
                run = bytearray()
            out.append(self.text[i])
        if run:
            out.append(run.decode("utf-8", "surrogatepass"))
        return "".join(out).replace(MARK, " ").removeprefix(" ")


@lru_cache(maxsize=2)
def load(path: str) -> Pieces:
    return Pieces(path)


def words_of(text: str) -> list[str]:
    """Words with the mark; marks inside the text count as blanks."""
    return [MARK + w for w in text.replace(MARK, " ").translate(_BLANK).split(" ") if w]


def units_of(text: str) -> list[str]:
    """The whole text with its white space; marks inside it count as blanks."""
    return UNIT.findall(MARK + text.replace(" ", MARK)) if text else []


_BLANK = {c: " " for c in (9, 10, 11, 12, 13)}
