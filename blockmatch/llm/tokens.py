"""Exact token ids of whole texts at the cost of a dictionary look-up a word.

The tokenizers library runs once for each distinct piece; a text's ids are the
concatenation of its pieces' ids. Cuts are made only where the tokenizer itself
always cuts, so the result equals encoding the whole text:

* `word` vocabularies drop white space, so every blank or line break is a cut;
* `byte` vocabularies glue one blank to the word behind it, so the cut lies
  before a blank or line break between two characters that aren't white space.
  A text in which a piece is empty or touches other white space is encoded whole.

A text that holds an added token (such as an end sign) is encoded whole, too.

At `most` pieces the less used half is forgotten, so memory is bounded.
"""

from __future__ import annotations

import os
import string
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import KEPT

#: Pieces that an encoder remembers.
MOST = 700_000
#: Characters at the end of a piece that are a token of their own behind letters (no apostrophe: contractions).
_TAIL = string.punctuation.replace("'", "")


def _byte_letters() -> dict[int, int]:
    """The printable stand-in of each byte in byte-level vocabularies: itself where visible, else the next free code point from 256."""
    seen = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = [b for b in range(256) if b not in seen]
    return {b: 256 + i for i, b in enumerate(rest)}


_LETTERS = _byte_letters()
#: Letters beyond ASCII that are looked up plainly (none is changed by composition), and the stand-ins of their bytes.
_LATIN = 0x250
_STAND_INS = {chr(c): "".join(chr(_LETTERS.get(b, b)) for b in chr(c).encode()) for c in range(_LATIN)}


class _Table(dict):
    """Row of each piece; row 0 says that its text must be encoded whole. `sign` stands for the blank before the piece."""

    def __init__(self, owner: PieceEncoder, blank: str):
        self.owner, self.blank, self.sign = owner, blank, blank.replace(" ", "Ġ")

    def __missing__(self, piece: str) -> int:
        owner = self.owner
        flat, starts = owner.flat, owner.starts
        core = piece.rstrip(_TAIL)
        plain = core.isalpha() and (core.isascii() or owner.latin(core))
        if plain and len(core) < len(piece):  # what is behind is tail signs
            at = self[core]
            flat.extend(flat[starts[at] : starts[at + 1]])
            flat.frombytes(owner.tails[piece[len(core) :]])
        elif plain:
            flat.fromlist([t.id for t in owner.tokenize(owner.letters(core, self))])
        elif (parts := owner.parts(piece, self)) is None:
            self[piece] = 0
            return 0
        else:
            for part in parts:
                flat.extend(part)
        starts.append(len(flat))
        self[piece] = at = len(starts) - 2
        return at


class _Tails(dict):
    def __init__(self, owner: PieceEncoder):
        self.owner = owner

    def __missing__(self, tail: str) -> bytes:
        self[tail] = ids = self.owner.pack(self.owner.whole(tail))
        return ids


class PieceEncoder:
    def __init__(self, path: str, most: int = MOST):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        # tokens matched in the raw text before it is cut; with one of them it is encoded whole
        self.added = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.most = most
        self.tokenize = self.tokenizer.model.tokenize
        self.keeps_space = self.tokenizer.normalizer is None
        self.kind = "H" if self.tokenizer.get_vocab_size() < 1 << 16 else "I"
        self.inner, self.first, self.tails = _Table(self, " "), _Table(self, ""), _Tails(self)
        self.clear()

    def clear(self) -> None:
        self.flat, self.starts, self.uses = array(self.kind), array("q", [0, 0]), np.zeros(1024, np.int64)
        for table in (self.inner, self.first, self.tails):
            table.clear()

    def shrink(self) -> None:
        """Forget the pieces that were used least, half of them or more."""
        n = len(self.starts) - 1
        uses = self.uses[:n].copy()
        keep = uses > max(1, int(np.partition(uses, n // 2)[n // 2]))
        if keep.sum() > n // 2:  # a tie
            keep[:] = False
        keep[0] = True
        start = np.array(self.starts, np.int64)
        size = np.where(keep, np.diff(start), 0)
        low, n_ids = start[:-1][keep], size[keep]
        ends = np.cumsum(n_ids)
        at = np.repeat(low - (ends - n_ids), n_ids) + np.arange(ends[-1] if len(ends) else 0)
        flat = np.array(self.flat, self.kind)[at]
        to = np.cumsum(keep) - 1
        for table in (self.inner, self.first):
            held = {piece: int(to[row]) for piece, row in table.items() if keep[row]}
            table.clear()
            table.update(held)
        self.tails.clear()
        self.flat, self.starts = array(self.kind, flat.tobytes()), array("q", np.concatenate(([0], ends)).astype(np.int64).tobytes())
        self.uses = np.concatenate((uses[keep] // 2, np.zeros(1024, np.int64)))

    def pack(self, ids: list[int]) -> bytes:
        return array(self.kind, ids).tobytes()

    def whole(self, text: str) -> list[int]:
        return self.tokenizer.encode(text, add_special_tokens=False).ids

    def latin(self, core: str) -> bool:
        """Whether a word beyond ASCII is one of letters whose lower case is known."""
        return max(core) < chr(_LATIN) and (self.keeps_space or core.lower().isalpha())

    def letters(self, core: str, table: _Table) -> str:
        """A bare word as the model's letters."""
        if core.isascii():
            return table.sign + core if self.keeps_space else core.lower()
        if self.keeps_space:
            return table.sign + "".join(map(_STAND_INS.__getitem__, core))
        return core.lower().encode().decode("latin-1").translate(_LETTERS)

    def parts(self, piece: str, table: _Table) -> list[array] | None:
        """Ids of a piece that isn't a bare word, in parts; None if its text must be encoded whole."""
        if not self.keeps_space:
            return [array(self.kind, self.whole(piece))] if piece else []
        if not piece or piece[-1].isspace():
            return None
        if piece[0] == "\n" and not piece[1].isspace():
            at = self.first[piece[1:]]
            return [array(self.kind, self.tails["\n"]), self.flat[self.starts[at] : self.starts[at + 1]]] if at else None
        return None if piece[0].isspace() else [array(self.kind, self.whole(table.blank + piece))]

    def rows_of(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Rows of the pieces of all texts, one behind the other, and the number of pieces of each text; only distinct pieces are looked up."""
        texts = pc.replace_substring(texts, "\n", " \n" if self.keeps_space else " ")
        cut = pc.split_pattern(texts, " ")
        ends = cut.offsets.to_numpy()
        size, pieces = np.diff(ends), cut.values.slice(ends[0], ends[-1] - ends[0]).dictionary_encode()
        code = pieces.indices.to_numpy()
        if not self.keeps_space:
            return self._looked_up(self.first, pieces.dictionary)[code], size
        # a text's first piece has no blank before it
        start = (ends[:-1] - ends[0])[size > 0]
        inner = np.ones(len(code), bool)
        inner[start] = False
        asked = np.bincount(code[inner], minlength=len(pieces.dictionary)) > 0
        of = np.zeros(len(asked), np.int64)
        of[asked] = self._looked_up(self.inner, pieces.dictionary.filter(pa.array(asked)))
        row = of[code]
        row[start] = self._looked_up(self.first, pieces.dictionary.take(pa.array(code[start])))
        return row, size

    def _looked_up(self, table: _Table, pieces: pa.Array) -> np.ndarray:
        return np.fromiter(map(table.__getitem__, pieces.to_numpy(zero_copy_only=False).tolist()), np.int64, len(pieces))

    def encode(self, texts: list[str] | pa.Array) -> list[np.ndarray]:
        """Ids of each text as unsigned 32-bit integers."""
        if len(self.starts) > self.most:
            self.shrink()
        texts = pa.array(texts, pa.large_string()) if isinstance(texts, list) else texts.cast(pa.large_string())
        row, size = self.rows_of(texts)
        flat, start = np.frombuffer(self.flat, self.kind), np.frombuffer(self.starts, np.int64)
        used = np.bincount(row, minlength=1)
        if len(used) > len(self.uses):
            self.uses = np.concatenate((self.uses, np.zeros(max(len(used), len(self.uses)), np.int64)))
        self.uses[: len(used)] += used
        low = start[row]
        n = start[row + 1] - low if len(row) else row
        ends = np.cumsum(n)
        if len(ends) and ends[-1]:
            at = np.repeat(low - (ends - n), n)
            at += np.arange(ends[-1])
            ids = flat[at].astype(np.uint32)
        else:
            ids = np.zeros(0, np.uint32)
        del flat, start  # else the arrays can't grow
        edges = np.concatenate(([0], ends))[np.concatenate(([0], np.cumsum(size)))]
        out = [ids[a:b] for a, b in zip(edges[:-1].tolist(), edges[1:].tolist())]
        odd = set()
        for added in self.added:
            odd.update(np.flatnonzero(pc.match_substring(texts, added).to_numpy(zero_copy_only=False)).tolist())
        if self.keeps_space:
            odd.update(np.repeat(np.arange(len(texts)), size)[row == 0].tolist())
            odd.update(np.flatnonzero(pc.match_substring(texts, " \n").to_numpy(zero_copy_only=False)).tolist())  # else it looks like a line break alone
        for i in odd:
            out[i] = np.array(self.whole(texts[i].as_py()), np.uint32)
        return out


_ENCODERS: dict[str, PieceEncoder] = {}


KEPT.append(_ENCODERS.clear)


def encoder(path: str, most: int = MOST) -> PieceEncoder:
    """The encoder of a vocabulary file in this worker process, kept between tasks."""
    if path not in _ENCODERS:
        _ENCODERS[path] = PieceEncoder(path, most)
    return _ENCODERS[path]
