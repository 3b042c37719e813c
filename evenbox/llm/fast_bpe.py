"""Whole-text token ids of the public tokenizers, fast enough for a corpus.

The ids are those of ``Tokenizer.encode(text, add_special_tokens=False)`` of the file as it is. Both vocabularies split a text at a lone space (or newline, for the word
vocabulary) whatever stands around it, so a text is cut there, each distinct piece is encoded once
by the library's own BPE model and remembered, and a call costs a dictionary lookup for each distinct piece of its texts.
Pieces outside the plain Latin alphabet, texts whose spaces touch other white space, and texts that
hold the string of an added token, go through the library's full pipeline. Tests hold both paths against the library.
"""

from __future__ import annotations

import re
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Letters of the plain path; fixed values.
_LETTERS = "A-Za-zÀ-ÖØ-öø-ÿ"
_PLAIN = re.compile(f"[!-~{_LETTERS}\n]+")
_CONTRACTIONS = "'s|'t|'re|'ve|'m|'ll|'d"
#: NUL stands between pieces that are scanned together; plain pieces have none.
_BYTE_PIECES = re.compile(f"\0|{_CONTRACTIONS}| ?[{_LETTERS}]+| ?[0-9]+| ?[^\\s\0{_LETTERS}0-9]+|\\s+(?![^\\s\0])|\\s+")
_WORD_PIECES = re.compile(f"\0|{_CONTRACTIONS}|[{_LETTERS}]+|[0-9]|[^\\s\0{_LETTERS}0-9]+")


def _byte_alphabet() -> dict[int, str]:
    """The visible character that stands for each byte in byte-level BPE vocabularies."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in shown]
    return {b: chr(b) for b in shown} | {b: chr(256 + k) for k, b in enumerate(hidden)}


class CorpusEncoder:
    """``encode_many(texts) -> [bytes of ids]``, little-endian, ``dtype`` wide.

    name: file in the public tokenizer folder. remember: pieces kept in memory; when they are that
    many, the later half is forgotten (frequent pieces are met early), so memory stays bounded.
    """

    def __init__(self, name: str, remember: int = 600_000):
        import public_tokenizers
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(public_tokenizers.path(name))
        added = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self._added = re.compile("|".join(map(re.escape, added)) or r"(?!)")
        self.size = self.library.get_vocab_size(with_added_tokens=True)
        self.code = "H" if self.size <= 1 << 16 else "I"
        self.dtype = np.dtype("<u2") if self.code == "H" else np.dtype("<u4")
        self.words = self.library.normalizer is not None
        self.remember = remember
        self._tokenize = self.library.model.tokenize
        #: code points that stand for bytes; NUL stays, between pre-tokens
        self._shown = np.array([0, *(ord(c) for _, c in sorted(_byte_alphabet().items())[1:])], "<u4")
        self._known: dict[str, bytes] = {}
        self._pre: dict[str, bytes] = {}

    def whole(self, text: str) -> bytes:
        """The library's full pipeline on one text."""
        return array(self.code, self.library.encode(text, add_special_tokens=False).ids).tobytes()

    def _learn(self, pieces: set[str]) -> None:
        """Encode new pieces, each standing after a space, all in one scan of their pre-tokens."""
        if "" in pieces:
            self._known[""] = b""
            pieces.discard("")
        plain = list(pieces)
        if not _PLAIN.fullmatch("\n".join(plain)):
            for piece in plain:
                if not _PLAIN.fullmatch(piece):
                    self._known[piece] = self.whole(piece if self.words else " " + piece)
                    pieces.discard(piece)
            plain = list(pieces)
        if not plain:
            return
        # a piece of letters alone is one pre-token
        letters = [p for p in plain if p.isalpha()]
        self._known.update(zip(letters, self._encoded([p.lower() for p in letters] if self.words else [f" {p}" for p in letters]), strict=True))
        mixed = [p for p in plain if not p.isalpha()]
        if not mixed:
            return
        if self.words:
            found = _WORD_PIECES.findall("\0".join(mixed).lower())
        else:
            found = _BYTE_PIECES.findall(" " + "\0 ".join(mixed))
        known = self._pre
        known["\0"] = b""
        fresh = list({t for t in found if t not in known})
        known.update(zip(fresh, self._encoded(fresh), strict=True))
        ids = list(map(known.__getitem__, found))
        ends = np.concatenate([[0], np.cumsum(np.fromiter(map(len, ids), np.int64, len(ids)))])
        between = np.flatnonzero([t == "\0" for t in found])
        begins, stops = ends[np.concatenate([[0], between])].tolist(), ends[np.append(between, len(found))].tolist()
        joined = b"".join(ids)
        self._known.update((piece, joined[i:j]) for piece, i, j in zip(mixed, begins, stops, strict=True))

    def _encoded(self, texts: list[str]) -> list[bytes]:
        """The ids of pre-tokens, each by itself; none holds a NUL."""
        if not texts:
            return []
        shown = self._shown[np.frombuffer("\0".join(texts).encode(), np.uint8)].tobytes().decode("utf-32-le").split("\0")
        tokenize, code = self._tokenize, self.code
        return [array(code, [t.id for t in tokenize(x)]).tobytes() for x in shown]

    def encode_many(self, texts: list[str | None]) -> list[bytes]:
        """The ids of each text; a null text has none.

        Arrow splits the texts and numbers the distinct pieces, so a piece is looked up once for all texts."""
        for known, most in ((self._known, self.remember), (self._pre, self.remember // 2)):
            if len(known) > most:
                for piece in list(known)[most // 2 :]:
                    del known[piece]
        plain = [row for row, text in enumerate(texts) if text and not self._added.search(text)]
        out: list[bytes | None] = [None] * len(texts)
        if plain:
            for row, ids in zip(plain, self._from_pieces([texts[row] for row in plain]), strict=True):
                out[row] = ids
        return [self.whole(text or "") if ids is None else ids for text, ids in zip(texts, out, strict=True)]

    def _from_pieces(self, texts: list[str]) -> list[bytes | None]:
        """The ids of texts without added tokens; None where a text cannot be cut safely."""
        cut = pc.split_pattern(pa.array([t.replace("\n", " ") for t in texts] if self.words else texts, pa.large_string()), " ")
        first = cut.offsets.to_numpy()
        numbered = cut.flatten().dictionary_encode()
        number = numbered.indices.to_numpy()
        heads: list[str] = []
        if not self.words:  # a text's first piece stands after no space
            own = np.ones(len(number), bool)
            own[first[:-1]] = False
            heads = numbered.take(pa.array(first[:-1])).to_pylist()
            number, first = number[own], first - np.arange(len(first))
        pieces = numbered.dictionary.to_numpy(zero_copy_only=False).tolist()
        ids = list(map(self._known.get, pieces))
        asked = np.zeros(len(pieces), bool)
        asked[number] = True
        missing = {p for p, known, here in zip(pieces, ids, asked.tolist(), strict=True) if here and known is None}
        if not self.words:  # a space beside other white space is no safe place
            missing = {p for p in missing if p and not p[0].isspace() and not p[-1].isspace()}
        if missing:
            self._learn(missing)
            ids = list(map(self._known.get, pieces))
        joined = pa.array(ids, pa.large_binary()).take(pa.array(number))
        unsafe = np.concatenate([[0], np.cumsum(joined.is_null().to_numpy(zero_copy_only=False))])[first]
        _, places, data = joined.buffers()
        at = np.frombuffer(places, np.int64)[first] if places is not None and len(joined) else np.zeros(len(first), np.int64)
        data = memoryview(data) if data is not None else b""
        out: list[bytes | None] = [None if unsafe[row] < unsafe[row + 1] else bytes(data[at[row] : at[row + 1]]) for row in range(len(texts))]
        for row, head in enumerate(heads):
            if not head or out[row] is None:
                continue
            out[row] = None if head[-1].isspace() and first[row] < first[row + 1] else self.whole(head) + out[row]
        return out


_encoders: dict[str, CorpusEncoder] = {}


def encoder(name: str) -> CorpusEncoder:
    """The worker's encoder of that vocabulary, made once."""
    if name not in _encoders:
        _encoders[name] = CorpusEncoder(name)
    return _encoders[name]
