"""Byte-level BPE of a public vocabulary: piece splitting, and exact encoding by per-prefix dynamic programming.

A text is cut at the special strings, then into pieces by the vocabulary's pattern; BPE never
crosses a piece.  Inside a piece, every prefix has exactly one token that its encoding can end
with: among the vocabulary entries that are suffixes of the prefix (found by a suffix-matching
automaton) it is the one that can stand after the last token of the prefix before it.  Back-pointers
from the end give the ids.  Two tokens can stand together when no merge across their border
comes before the merges that build them.
"""

from __future__ import annotations

import json
import re
from array import array

import ahocorasick
import numpy as np
import regex

if array("I", [1]).tobytes() != b"\1\0\0\0":
    raise ImportError("needs a little-endian machine with 32-bit unsigned int")

#: Fixed value: the pattern that the byte-level pre-tokenizer of the file names only by ``use_regex``.
PIECE_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"

#: Characters outside these ranges may be classed otherwise by another Unicode version; texts that
#: hold one are cut by the library itself.
_RARE = re.compile(
    "[^\u0000-՗؀-ۿऀ-௿฀-๿Ḁ-₎₠-꓏가-힣豈-﫿︀-￿\U0001f300-\U0001faff]"
)

#: The same pattern for the faster engine of the standard library, whose letters, digits and white
#: space agree with the pattern's classes for texts of these characters only.
_PLAIN_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+"
_NOT_PLAIN = re.compile("[^\0-\x1b\x20-\x84\x86-\x9f\xa1-\xb1\xb4-\xb8\xba\xbb\xbf-\u02ff\u0391-\u03ff\u0410-\u044f]")

#: Longest piece, and numbers of pieces (encoded one by one, and together) and of token pairs, that memos keep.
MEMO_PIECE, MEMO_FEW, MEMO_SIZE, MEMO_PAIRS = 64, 250_000, 800_000, 300_000


def _byte_letters() -> dict[str, int]:
    """The letter that stands for each byte in a byte-level vocabulary file: printable bytes stand for
    themselves, the others follow from U+0100 in ascending order."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class Vocabulary:
    """Vocabulary and merges of a tokenizers file with a byte-level BPE model and no normaliser."""

    def __init__(self, text: str):
        self.source = text
        spec = json.loads(text)
        model = spec["model"]
        if model["type"] != "BPE" or (spec.get("pre_tokenizer") or {}).get("type") != "ByteLevel" or spec.get("normalizer"):
            raise ValueError("not a byte-level BPE without normaliser")
        letters = _byte_letters()
        self.ids = {bytes(letters[c] for c in token): i for token, i in model["vocab"].items()}
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        size = max([*self.ids.values(), *self.special.values()]) + 1
        self.bytes: list[bytes] = [b""] * size
        for token, i in self.ids.items():
            self.bytes[i] = token
        for token, i in self.special.items():
            self.bytes[i] = token.encode()
        self.sizes = np.array([len(b) for b in self.bytes])
        self.merge: dict[tuple[int, int], int] = {}  # pair of ids -> rank
        self.parts: dict[int, tuple[int, int, int]] = {}  # id -> left, right, rank
        name = model["vocab"]
        for rank, pair in enumerate(model["merges"]):
            left, right = pair if isinstance(pair, list) else pair.split(" ")
            a, b, made = name[left], name[right], name[left + right]
            self.merge[a, b] = rank
            self.parts.setdefault(made, (a, b, rank))
        self.cut_at = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.pattern, self.plain_pattern = regex.compile(PIECE_PATTERN), re.compile(_PLAIN_PATTERN)
        self._library = None

    @property
    def library(self):
        """The tokenizers library's own object for this file."""
        if self._library is None:
            from tokenizers import Tokenizer

            self._library = Tokenizer.from_str(self.source)
            self._library.no_truncation()
            self._library.no_padding()
        return self._library

    def pieces(self, text: str) -> list[str]:
        """Pieces of a text that holds no special string."""
        if _NOT_PLAIN.search(text) is None:
            return self.plain_pattern.findall(text)
        if _RARE.search(text) is None:
            return self.pattern.findall(text)
        cut = self.library.pre_tokenizer.pre_tokenize_str(text)
        return [text[a:b] for _, (a, b) in cut]


class PrefixEncoder:
    """Exact ids of a piece by dynamic programming over its prefixes."""

    def __init__(self, vocabulary: Vocabulary):
        self.v = vocabulary
        self.automaton = ahocorasick.Automaton()
        for token, i in vocabulary.ids.items():
            self.automaton.add_word(token.decode("latin-1"), (len(token), i))
        self.automaton.make_automaton()
        self.fits: dict[tuple[int, int], bool] = {}
        self.edges: dict[tuple[int, int], list[tuple[int, float]]] = {}

    def edge(self, token: int, side: int) -> list[tuple[int, float]]:
        """Nodes on the left (0) or right (1) edge of a token's merge tree, each with the rank of the merge that uses it up."""
        if (token, side) not in self.edges:
            nodes, node, end = [(token, float("inf"))], token, float("inf")
            while node in self.v.parts:
                rank = self.v.parts[node][2]
                node, end = self.v.parts[node][side], rank
                nodes.append((node, end))
            self.edges[token, side] = nodes
        return self.edges[token, side]

    def compatible(self, a: int, b: int) -> bool:
        """Whether ``b`` can follow ``a``: no pair across the border merges while both of its sides still stand.

        Equal ranks merge from the left, so a pair across the border loses to its left side's
        own merge and wins over its right side's.
        """
        known = self.fits.get((a, b))
        if known is None:
            rank = self.v.merge.get
            known = True
            right = self.edge(b, 0)
            for x, x_end in self.edge(a, 1):
                for y, y_end in right:
                    at = rank((x, y))
                    if at is not None and at < x_end and at <= y_end:
                        known = False
                        break
                if not known:
                    break
            if len(self.fits) >= MEMO_PAIRS:
                self.fits.clear()
            self.fits[a, b] = known
        return known

    def encode(self, piece: bytes) -> list[int]:
        """Ids of a piece; one that no tokens make up raises."""
        whole = self.v.ids.get(piece)
        if whole is not None:
            return [whole]
        n = len(piece)
        last = [-1] * (n + 1)  # the one token that the encoding of each prefix ends with
        size = [0] * (n + 1)
        for end, (length, token) in self.automaton.iter(piece.decode("latin-1")):
            end += 1
            if last[end] < 0:
                start = end - length
                if start == 0 or last[start] >= 0 and self.compatible(last[start], token):
                    last[end], size[end] = token, length
        if last[n] < 0:
            raise ValueError(f"the vocabulary has no tokens for the piece {piece!r}")
        ids = []
        while n:
            ids.append(last[n])
            n -= size[n]
        return ids[::-1]


class LibraryEncoder:
    """Ids of a piece from the tokenizers library."""

    def __init__(self, vocabulary: Vocabulary):
        self.v = vocabulary

    def encode_all(self, pieces: list[str]) -> list[bytes]:
        """Packed ids of each piece.

        Words of letters are encoded as one text of many words, which the pattern cuts at the same
        places; byte lengths tell where each word's ids end.
        """
        out: dict[str, bytes] = {}
        words = [p for p in pieces if p.isalpha() or p[0] == " " and p[1:].isalpha()]
        if _NOT_PLAIN.search("".join(words)) is not None:
            words = [p for p in words if _NOT_PLAIN.search(p) is None]
        for at in range(0, len(words), 2000):
            part = words[at : at + 2000]
            # every word follows a line break, which is a piece of its own before a letter or a blank
            text = "\n".join(["", *part])
            ids = np.array(self.v.library.encode_batch_fast([text], add_special_tokens=False)[0].ids, "<u4")
            ends = np.cumsum(self.v.sizes[ids])
            raw = np.frombuffer(text.encode(), np.uint8)
            stops = np.append(np.flatnonzero(raw == 10)[1:], len(raw))
            last = np.searchsorted(ends, stops) + 1
            first = np.concatenate([[0], last[:-1]]) + 1  # without the line break
            packed = ids.tobytes()
            out.update(zip(part, [packed[4 * x : 4 * y] for x, y in zip(first.tolist(), last.tolist())]))
        rest = [p for p in pieces if p not in out]
        for at in range(0, len(rest), 10_000):
            part = rest[at : at + 10_000]
            for piece, found in zip(part, self.v.library.encode_batch_fast(part, add_special_tokens=False)):
                out[piece] = array("I", found.ids).tobytes()
        return [out[p] for p in pieces]

    def encode(self, piece: bytes) -> list[int]:
        whole = self.v.ids.get(piece)
        return [whole] if whole is not None else self.v.library.encode(piece.decode(), add_special_tokens=False).ids


class Coder(dict):
    """Text to ids and back; keeps the ids of short pieces, as little-endian unsigned 32-bit integers.

    Packing relies on the machine's own order being little-endian, which is checked on import.
    """

    def __init__(self, vocabulary: Vocabulary, encoder=PrefixEncoder):
        super().__init__()
        self.v, self.encoder, self.old = vocabulary, encoder(vocabulary), {}

    def __missing__(self, piece: str) -> bytes:
        ids = array("I", self.encoder.encode(piece.encode())).tobytes()
        if len(piece) <= MEMO_PIECE:
            if len(self) >= MEMO_FEW and not self.old:
                self.clear()
            self[piece] = ids
        return ids

    def trim(self) -> None:
        """Give memory back between tasks: a worker process goes on to other work."""
        self.clear()
        self.old = {}
        if isinstance(self.encoder, PrefixEncoder):
            self.encoder.fits.clear()

    def packed(self, text: str | None) -> bytes:
        """Ids of a whole text, packed; null counts as empty."""
        if not text:
            return b""
        get = self.__getitem__
        if self.v.cut_at is None or not any(s in text for s in self.v.special):
            return b"".join(map(get, self.v.pieces(text)))
        parts = self.v.cut_at.split(text)
        out = []
        for i, part in enumerate(parts):
            out += [np.uint32(self.v.special[part]).tobytes()] if i % 2 else map(get, self.v.pieces(part)) if part else []
        return b"".join(out)

    def packed_all(self, texts: list[str | None]) -> list[bytes]:
        """``packed`` of several texts; pieces met for the first time are encoded together, by the library."""
        get, rows, new = self.get, [], set()
        for text in texts:
            if not text or self.v.cut_at is not None and any(s in text for s in self.v.special):
                rows.append((None, None, None))
                continue
            pieces = self.v.pieces(text)
            ids = list(map(get, pieces))
            gaps, at = [], -1
            for _ in range(ids.count(None)):
                at = ids.index(None, at + 1)
                gaps.append(at)
            new.update([pieces[i] for i in gaps])
            rows.append((pieces, ids, gaps))
        if len(self) + len(new) > MEMO_SIZE:  # pieces of the last round stay within reach
            self.old = dict(self)
            self.clear()
        kept = {p: self.old[p] for p in new if p in self.old}
        self.update(kept)
        met = [p for p in new if p not in kept]
        self.update(zip(met, self.encoder.encode_all(met)))
        out = []
        for text, (pieces, ids, gaps) in zip(texts, rows):
            if pieces is None:
                out.append(self.packed(text))
                continue
            for i in gaps:
                ids[i] = self[pieces[i]]  # a piece that was cleared meanwhile is encoded again
            out.append(b"".join(ids))
        for piece in [p for p in met if len(p) > MEMO_PIECE]:
            self.pop(piece, None)
        return out

    def decoded(self, packed: bytes) -> str:
        """The text of packed ids; bytes that are no UTF-8 become U+FFFD."""
        return b"".join(map(self.v.bytes.__getitem__, np.frombuffer(packed, "<u4").tolist())).decode("utf-8", "replace")


def read_vocabulary(path: str, limit: int = 64 << 20) -> str:
    """Content of a vocabulary file on the driver; its size is checked, as every task gets it."""
    with open(path, encoding="utf-8") as file:
        text = file.read(limit + 1)
    if len(text) > limit:
        raise ValueError(f"vocabulary file of over {limit} characters")
    return text


_KEPT: dict = {}


def coder(source, encoder=PrefixEncoder) -> Coder:
    """The worker process's coder for a broadcast vocabulary file; kept between tasks."""
    key = (hash(source.value), encoder.__name__)
    if key not in _KEPT:
        _KEPT.clear()
        _KEPT[key] = Coder(Vocabulary(source.value), encoder)
    return _KEPT[key]
