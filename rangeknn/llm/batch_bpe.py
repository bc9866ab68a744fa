"""Byte-pair merging of many short pieces at once, for vocabularies in the tokenizers format.

Gives the library's ids (lowest merge first, leftmost among equals) for pieces whose normal form is
certain; what has other characters, special strings or great length goes to the library.
"""

from __future__ import annotations

import json
import re
from pathlib import Path

import numpy as np
import regex

NONE = np.int32(2**31 - 1)
#: Letters up to here compose and change case one by one (U+0130 apart).
_PLAIN = re.compile("[\t-~¡-¬®-įı-ɏ]*")


def byte_letters() -> list[str]:
    """The printable letter that byte-level vocabularies write for each byte."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    letter = {b: chr(b) for b in shown}
    for i, b in enumerate(b for b in range(256) if b not in letter):
        letter[b] = chr(256 + i)
    return [letter[b] for b in range(256)]


class PairTable:
    """(left id, right id) -> rank of their merge, by open addressing over arrays."""

    def __init__(self, left: np.ndarray, right: np.ndarray) -> None:
        self.bits = max(4, int(len(left) * 4).bit_length())
        self.keys = np.full(1 << self.bits, -1, np.int64)
        self.ranks = np.full(1 << self.bits, NONE, np.int32)
        key = left.astype(np.int64) << 32 | right
        for k, at, rank in zip(key.tolist(), self._slot(key).tolist(), range(len(key)), strict=True):
            while self.keys[at] >= 0:
                at = (at + 1) & (len(self.keys) - 1)
            self.keys[at], self.ranks[at] = k, rank

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return (key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.bits)).astype(np.int64)

    def find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left.astype(np.int64) << 32 | np.maximum(right, 0)
        at = self._slot(key)
        out = np.where(self.keys[at] == key, self.ranks[at], NONE)
        more = np.flatnonzero((self.keys[at] != key) & (self.keys[at] >= 0))
        while len(more):
            at[more] = (at[more] + 1) & (len(self.keys) - 1)
            seen = self.keys[at[more]]
            hit = seen == key[more]
            out[more[hit]] = self.ranks[at[more[hit]]]
            more = more[~hit & (seen >= 0)]
        out[(left < 0) | (right < 0)] = NONE
        return out


class BatchBpe:
    """encode_many(words) -> ids as little-endian bytes, as ``Tokenizer.encode`` gives them."""

    def __init__(self, path: str, longest: int = 48) -> None:
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        spec = json.loads(Path(path).read_text())
        model, vocab = spec["model"], spec["model"]["vocab"]
        suffix = model.get("end_of_word_suffix") or ""
        merges = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        ids = np.array([(vocab[a], vocab[b], vocab[a + b]) for a, b in merges], np.int64)
        self.pairs, self.merged = PairTable(ids[:, 0], ids[:, 1]), ids[:, 2].astype(np.int32)
        letters = byte_letters()
        self.inner = np.array([vocab[x] for x in letters], np.int32)
        self.final = np.array([vocab[x + suffix] for x in letters], np.int32)
        self.specials = re.compile("|".join(re.escape(t["content"]) for t in spec.get("added_tokens", [])) or "(?!)")
        self.words = bool(suffix)
        if self.words:
            self.find = regex.compile(next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")).findall
        else:
            self.find = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+").findall
        self.longest = longest

    def merge(self, pieces: list[bytes]) -> list[bytes]:
        """Ids of short pieces; those of like length go together."""
        size = np.fromiter(map(len, pieces), np.int64, len(pieces))
        order = np.argsort(size, kind="stable")
        out: list[bytes] = [b""] * len(pieces)
        for a in range(0, len(order), 4096):
            rows = order[a : a + 4096].tolist()
            n = size[rows]
            width = int(n.max(initial=0))
            if not width:
                continue
            inside = np.arange(width)[None, :] < n[:, None]
            raw = np.zeros((len(rows), width), np.uint8)
            raw[inside] = np.frombuffer(b"".join([pieces[i] for i in rows]), np.uint8)
            t = np.where(inside, self.inner[raw], -1).astype(np.int32)
            some = np.flatnonzero(n > 0)
            t[some, n[some] - 1] = self.final[raw[some, n[some] - 1]]
            left = n.copy()
            live = np.flatnonzero(n > 1)
            if width > 1:
                rank = np.full((len(rows), width), NONE, np.int32)
                rank[:, :-1] = self.pairs.find(t[:, :-1].ravel(), t[:, 1:].ravel()).reshape(len(rows), width - 1)
                while len(live):
                    r = rank[live]
                    at = r.argmin(axis=1)
                    best = r[np.arange(len(live)), at]
                    go = best < NONE
                    live, at, best, r = live[go], at[go], best[go], r[go]
                    if not len(live):
                        break
                    w = np.arange(width)[None, :]
                    x = t[live]
                    shifted = np.concatenate([x[:, 1:], np.full((len(live), 1), -1, np.int32)], axis=1)
                    x = np.where(w > at[:, None], shifted, x)
                    i = np.arange(len(live))
                    x[i, at] = self.merged[best]
                    shifted = np.concatenate([r[:, 1:], np.full((len(live), 1), NONE, np.int32)], axis=1)
                    r = np.where(w >= at[:, None], shifted, r)
                    nxt = np.where(at + 1 < width, x[i, np.minimum(at + 1, width - 1)], -1)
                    r[i, at] = self.pairs.find(x[i, at], nxt)
                    has = np.flatnonzero(at > 0)
                    r[has, at[has] - 1] = self.pairs.find(x[has, at[has] - 1], x[has, at[has]])
                    t[live], rank[live] = x, r
                    left[live] -= 1
            flat = t[np.arange(width)[None, :] < left[:, None]].astype("<u4").tobytes()
            ends = np.cumsum(left * 4).tolist()
            start = 0
            for i, end in zip(rows, ends, strict=True):
                out[i] = flat[start:end]
                start = end
        return out

    def encode_many(self, words: list[str]) -> list[bytes]:
        out: list[bytes] = [b""] * len(words)
        odd, pieces, owner = [], [], []
        find, specials, longest = self.find, self.specials.search, self.longest
        for i, word in enumerate(words):
            if not (word.isascii() and word.isprintable() or _PLAIN.fullmatch(word)) or len(word) > longest or "<|" in word and specials(word):
                odd.append(i)
                continue
            if self.words:
                word = word.lower()
                found = (word,) if word.isalpha() else find(word)
            else:
                found = (word,) if word[1:].isalpha() and (word[0] == " " or word[0].isalpha()) else find(word)
            for piece in found:
                pieces.append(piece.encode())
                owner.append(i)
        for i, ids in zip(owner, self.merge(pieces), strict=True):
            out[i] = out[i] + ids if out[i] else ids
        if odd:
            for i, e in zip(odd, self.library.encode_batch_fast([words[i] for i in odd], add_special_tokens=False), strict=True):
                out[i] = np.array(e.ids, "<u4").tobytes()
        return out
