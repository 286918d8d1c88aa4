"""Exact, memoised encoding with the tokenizers library.

Both vocabularies cut a text at white space before merging, so a text's ids are the ids of its
white-space pieces in order. Pieces are encoded by the library once and then looked up; a piece of
plain letters goes straight to the library's merge model. Texts whose white space is not single
spaces and line feeds, or that hold marks of special tokens, go through the library whole.
"""

from __future__ import annotations

import os
import struct

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Punctuation that can follow a word; an apostrophe could begin a contraction, so it is not here.
_TAIL = ".,!%*#$&;:?|()-"


def _byte_letters() -> dict[int, int]:
    """The byte-level alphabet: printable bytes stand for themselves, the others follow at 256."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {b: b for b in plain} | {b: 256 + i for i, b in enumerate(rest)}


_LETTERS = _byte_letters()
_SPACE = chr(_LETTERS[32])


def _plain(text: str) -> bool:
    """White space is only single spaces and line feeds between words, without special marks."""
    if "<|" in text or "  " in text or "\n\n" in text or " \n" in text or "\n " in text:
        return False
    return text.replace("\n", "x").isprintable() and not (text[0].isspace() or text[-1].isspace())


class _Memo(dict):
    """Ids of pieces as bytes, with the entries of the generation before."""

    def __init__(self, make, before: dict):
        self.make, self.before = make, before

    def __missing__(self, piece: str) -> bytes:
        ids = self.before.get(piece)
        if ids is None:
            ids = self.make(piece)
        self[piece] = ids
        return ids


class PieceEncoder:
    """Texts to little-endian uint32 bytes. Twice ``memo_limit`` pieces bound a worker's memory.

    ``spaced``: pieces keep the space before them and case matters, as in byte-level cutting;
    otherwise white space is dropped and letters are lower-cased.
    """

    def __init__(self, path: str, *, spaced: bool, memo_limit: int = 250_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.merge, self.pack = self.tokenizer.model.tokenize, struct.Struct("<I").pack
        self.packed = [self.pack(i) for i in range(max(self.tokenizer.get_vocab(True).values(), default=0) + 1)]
        self.spaced, self.memo_limit = spaced, memo_limit
        self.inner = _Memo(self._inner, {})  # after a space
        self.first = _Memo(self._first, {})  # at a line's start, and tails

    def _whole(self, text: str) -> bytes:
        return np.asarray(self.tokenizer.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def _merged(self, letters: str) -> bytes:
        packed, ids = self.packed, self.merge(letters)
        return packed[ids[0].id] if len(ids) == 1 else b"".join([packed[t.id] for t in ids])

    def _first(self, piece: str) -> bytes:
        stem = piece.rstrip(_TAIL)
        if self.spaced and stem.isalpha() and stem.isascii():
            return self._merged(stem) if stem == piece else self._merged(stem) + self.first[piece[len(stem) :]]
        return self._whole(piece)

    def _inner(self, piece: str) -> bytes:
        if piece.isalpha() and piece.isascii():
            return self._merged(_SPACE + piece if self.spaced else piece.lower())
        stem = piece.rstrip(_TAIL)
        if stem != piece and stem.isalpha():
            return self.inner[stem] + self.first[piece[len(stem) :]]
        if piece.isalpha():
            try:
                piece.encode("latin-1")  # letters whose lower case and composition are simple
            except UnicodeEncodeError:
                pass
            else:
                text = " " + piece if self.spaced else piece.lower()
                return self._merged(text.encode().decode("latin-1").translate(_LETTERS))
        return self._whole(" " + piece if self.spaced and piece else piece or (" " if self.spaced else ""))

    def _bound(self) -> None:
        if len(self.inner) > self.memo_limit:
            self.inner = _Memo(self._inner, dict(self.inner))
        if len(self.first) > self.memo_limit // 4:
            self.first = _Memo(self._first, {})

    def closed(self, texts: list[str], end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts in one array, each text closed by the end id, and their sizes. What
        the texts' pieces have in common is looked up once."""
        self._bound()
        # a tab is in no piece: it stands for the end, and with a number for a text that goes whole
        if self.spaced:  # and a carriage return is before what begins a line, and has no space
            lines = [f"\t{i} \t" if t and not _plain(t) else "\r" + t.replace("\n", " \n \r") + " \t" if t else "\t" for i, t in enumerate(texts)]
        else:
            lines = [f"\t{i} \t" if t and not _plain(t) else t.replace("\n", " ") + " \t" if t else "\t" for i, t in enumerate(texts)]
        lists = pc.split_pattern(pa.array(lines, pa.string()), " ")
        pieces = lists.flatten().dictionary_encode()
        names, others = pieces.dictionary.to_numpy(zero_copy_only=False).tolist(), {}
        for i in np.flatnonzero(pc.starts_with(pieces.dictionary, "\t").to_numpy(zero_copy_only=False)).tolist():
            others[i] = self.pack(end_id) if names[i] == "\t" else self._whole(texts[int(names[i])])
            names[i] = ""
        if self.spaced:
            for i in np.flatnonzero(pc.match_substring_regex(pieces.dictionary, "^[\r\n]").to_numpy(zero_copy_only=False)).tolist():
                others[i] = self.first[names[i].removeprefix("\r")]
                names[i] = ""
        bare = pc.utf8_rtrim(pieces.dictionary, characters=_TAIL)
        tails = {}
        for i in np.flatnonzero(pc.not_equal(bare, pieces.dictionary).to_numpy(zero_copy_only=False)).tolist():
            stem = names[i].rstrip(_TAIL)
            if stem.isalpha():
                tails[i], names[i] = names[i][len(stem) :], stem
        parts = list(map(self.inner.__getitem__, names))
        for i, tail in tails.items():
            parts[i] += self.first[tail]
        for i, ids in others.items():
            parts[i] = ids
        size = np.fromiter(map(len, parts), np.int64, len(parts)) // 4
        which = pieces.indices.to_numpy()
        length = size[which]
        stop = np.cumsum(length)
        place = np.arange(stop[-1] if len(stop) else 0) + np.repeat((np.cumsum(size) - size)[which] - (stop - length), length)
        edge = np.r_[0, stop][lists.offsets.to_numpy()]
        return np.frombuffer(b"".join(parts), "<u4")[place], np.diff(edge)

    def encode(self, texts: list[str]) -> list[bytes]:
        self._bound()
        inner, first, out = self.inner.__getitem__, self.first.__getitem__, []
        for text in texts:
            if not text:
                out.append(b"")
            elif not _plain(text):
                out.append(self._whole(text))
            elif self.spaced:
                parts = []
                for line in text.split("\n"):
                    head, _, rest = line.partition(" ")
                    parts.append(first(head))
                    if rest:
                        parts.extend(map(inner, rest.split(" ")))
                    parts.append(first("\n"))
                parts.pop()
                out.append(b"".join(parts))
            else:
                out.append(b"".join(map(inner, text.replace("\n", " ").split(" "))))
        return out


_ENCODERS: dict[tuple, PieceEncoder] = {}


def encoder(path: str, spaced: bool) -> PieceEncoder:
    """One encoder for each worker process."""
    if (path, spaced) not in _ENCODERS:
        _ENCODERS[(path, spaced)] = PieceEncoder(path, spaced=spaced)
    return _ENCODERS[(path, spaced)]


def forget() -> None:
    """Drops the encoders and their memos; for a worker whose stage has no text to encode."""
    _ENCODERS.clear()
