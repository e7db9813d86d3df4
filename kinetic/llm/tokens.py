"""Token ids of whole texts, by a public tokenizer file.

A text is cut before single spaces and line ends between other characters,
where byte-level BPE with the usual word pattern never joins anything; the ids
of each piece come from the tokenizers library once and are then kept per
worker. Texts with other runs of white space go to the library whole.
"""

from __future__ import annotations

import codecs
import json
import re
import zlib

import numpy as np

#: Appended to each document.
END_ID = 2


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


#: Pieces of letters, digits and signs that BPE itself cuts where the word pattern does: Latin letters, ASCII but apostrophes (which begin endings), after a line end or a space that is left out.
LATIN = re.compile("\n?[!-&(-~\u00aa\u00b5\u00ba\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f]+")
_SHOWN = {*range(33, 127), *range(161, 173), *range(174, 256)}
#: Byte-level BPE writes each byte that cannot be shown as a character from 256 on.
BYTE_CHARS = {b: 256 + i for i, b in enumerate(b for b in range(256) if b not in _SHOWN)}
#: The characters of all bytes, in their order.
SHOWN = "".join(chr(BYTE_CHARS.get(b, b)) for b in range(256))
_SPACE, _LINE = SHOWN[32], SHOWN[10]


def _kind(c: str) -> str:
    return c if c in (_SPACE, _LINE) else "letter" if c.isalpha() or not c.isascii() else "digit" if c.isdigit() else "sign"


def _latin(shown: str) -> bool:
    """Whether a token may be part of a piece of LATIN; True where that cannot be told."""
    try:
        text = bytes(SHOWN.index(c) for c in shown).decode()
    except ValueError:
        return True
    return all(p == "" or LATIN.fullmatch(p) for p in text.split(" "))


def cuts_itself(model) -> bool:
    """Whether a tokenizer is byte-level BPE whose merges, within and between pieces of LATIN, never join what the word pattern cuts."""
    kind = json.loads(model.to_str())
    cut, bpe = kind.get("pre_tokenizer") or {}, kind["model"]
    if kind.get("normalizer") is not None or cut.get("type") != "ByteLevel" or cut.get("add_prefix_space") or not cut.get("use_regex", True):
        return False
    if bpe["type"] != "BPE" or any(bpe.get(k) for k in ("ignore_merges", "dropout", "continuing_subword_prefix", "end_of_word_suffix")):
        return False
    merges = (m if isinstance(m, list) else m.split(" ") for m in bpe["merges"])
    across = ((a, b) for a, b in merges if _kind(a[-1]) != _kind(b[0]) and (a != _SPACE or b[0] == _LINE))
    return not any(_latin(a + b) for a, b in across) and len(model.encode("\n", add_special_tokens=False).ids) == 1


class Encoder:
    """ids as little-endian uint16 (or uint32 for larger vocabularies) bytes, equal to the library's for the whole text.

    Texts that hold the string of an added token go to the library whole, which
    reads it as that token. ``most`` bounds the pieces kept in each of two
    generations, by no less than what one chunk of texts holds: a full one
    becomes the old one, and what is asked for again moves over, so that
    frequent pieces stay.
    """

    #: New pieces that BPE reads as one string.
    TOGETHER = 128

    def __init__(self, path: str, most: int = 450_000):
        from tokenizers import Tokenizer

        self.model, self.most = Tokenizer.from_file(path), most
        self.added = [t.content for t in self.model.get_added_tokens_decoder().values() if t.content]
        vocab = self.model.get_vocab()
        self.dtype = np.dtype("<u2" if max(vocab.values()) < 65536 else "<u4")
        self.end = np.array([END_ID], self.dtype).tobytes()
        self.kept: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.cuts = cuts_itself(self.model)
        if self.cuts:
            self.bare = Tokenizer(self.model.model)  # the same merges, without the word pattern
            self.begins = np.zeros(max(vocab.values()) + 1, bool)
            self.begins[[i for t, i in vocab.items() if t[0] in (_SPACE, _LINE)]] = True
            self.line = self._plain(["\n"])[0]

    def _plain(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, self.dtype).tobytes() for e in self.model.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, pieces: set[str]) -> None:
        """Keeps the ids of new pieces. Those that are empty or begin or end with white space (but for one line end at the beginning) are left out."""
        kept, old, new, rare = self.kept, self.old, [], []
        for p in pieces:
            if p in old:
                kept[p] = old[p]
            elif LATIN.fullmatch(p):
                new.append(p)
            elif p and not p[-1].isspace() and not (p[1] if p[0] == "\n" else p[0]).isspace():
                rare.append(p)
        shown = []
        for at in range(0, len(new), self.TOGETHER):
            text = "".join([p if p[0] == "\n" else " " + p for p in new[at : at + self.TOGETHER]])
            shown.append(codecs.charmap_decode(text.encode(), "strict", SHOWN)[0])
        ids = np.array([i for e in self.bare.encode_batch_fast(shown, add_special_tokens=False) for i in e.ids], self.dtype)
        # each piece has one space or line end, which begins its first token
        at = [*(np.flatnonzero(self.begins[ids]) * self.dtype.itemsize).tolist(), ids.nbytes]
        flat = ids.tobytes()
        kept.update(zip(new, [flat[a:b] for a, b in zip(at, at[1:], strict=False)], strict=True))
        kept.update(zip(rare, self._plain([p if p[0] == "\n" else " " + p for p in rare]), strict=True))

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of each text, without END_ID."""
        if not self.cuts:
            return self._plain(texts)
        return [ids for part in small_chunks(texts, 2_000_000) for ids in self._chunk(texts[part])]

    def _chunk(self, texts: list[str]) -> list[bytes]:
        out, cut, odd = [b""] * len(texts), [], []
        for i, text in enumerate(texts):
            # two line ends in a row are cut between them, more are not
            if text[:1].isspace() or text[-1:] == "\n" or "\n " in text or "\n\n\n" in text or any(a in text for a in self.added):
                odd.append(i)
            elif text:
                # the first piece is read after a line end too, whose id is taken off again
                cut.append((i, ("\n" + text.replace("\n", " \n")).split(" ")))
        if len(self.kept) >= self.most:
            self.old, self.kept = self.kept, {}
        self.kept["\n"] = self.line
        self._learn(set().union(*[pieces for _, pieces in cut]).difference(self.kept))
        get = self.kept.__getitem__
        for i, pieces in cut:
            try:
                out[i] = b"".join(map(get, pieces))[len(self.line) :]
            except KeyError:  # spaces in a row, or beside other white space
                odd.append(i)
        for i, ids in zip(odd, self._plain([texts[i] for i in odd]), strict=True):
            out[i] = ids
        return out

    def documents(self, texts: list[str | None]) -> list[np.ndarray]:
        """ids of each document with END_ID; null is empty."""
        return [np.frombuffer(b + self.end, self.dtype) for b in self.encode([t or "" for t in texts])]


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """This worker's encoder for a tokenizer file."""
    import os

    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def crc32(ids: np.ndarray) -> int:
    return zlib.crc32(ids.astype("<u4").tobytes())


def small_chunks(texts: list[str | None], most: int = 4_000_000) -> list[slice]:
    """Runs of texts of about ``most`` characters."""
    out, start, size = [], 0, 0
    for i, t in enumerate(texts):
        size += len(t or "")
        if size >= most:
            out.append(slice(start, i + 1))
            start, size = i + 1, 0
    if start < len(texts):
        out.append(slice(start, len(texts)))
    return out
