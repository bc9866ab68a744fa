"""Splitting whole texts into memoisable segments, so that a tokenizer sees each form once.

Byte-level pre-tokenization never joins what stands on both sides of a single space between
two other characters: a text is cut before each such space and every segment is encoded on
its own. Segments repeat, as words do, so their encodings are kept in a memo of bounded size.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

#: A run of white space that holds a space and more: cutting at each space would change it.
_RUN = re.compile(r" \s|\s ")
_CUT = re.compile(r"(?<=\S)(?= \S)")
#: str.split() also cuts at these, which tokenizers do not count as white space.
_SEPARATORS = re.compile("[\x1c-\x1f]")
_WHITE = re.compile("[\t-\r \x85\xa0  -     　]+")


class SegmentEncoder:
    """Encodes texts by way of ``encode_many(list of segments) -> list of values``.

    ``spaced``: segments after a text's first keep the space they were cut at (byte-level
    vocabularies). Otherwise white space has no tokens and words stand alone. The memo holds
    at most about ``limit`` segments; when it is full its middle half goes, as the oldest ones
    are the most frequent.
    """

    def __init__(self, encode_many: Callable[[list[str]], list], spaced: bool, limit: int = 400_000) -> None:
        self.encode_many, self.spaced, self.limit = encode_many, spaced, limit
        self.memo: dict = {}

    def _cut(self, text: str) -> tuple[str | None, list[str]]:
        """The first segment (None if it is like the others) and the rest, without their space."""
        if not self.spaced:
            if _SEPARATORS.search(text):
                return None, [x for x in _WHITE.split(text) if x]
            return None, text.split()
        if text[:1] != " " and not _RUN.search(text):
            head, *rest = text.split(" ")
            return head, rest
        head, *rest = _CUT.split(text)
        return head, [x[1:] for x in rest]

    def values(self, texts: list[str], chunk: int = 500) -> Iterator[list]:
        """For each text the values of its segments in order."""
        memo, lead = self.memo, " " if self.spaced else ""
        for at in range(0, len(texts), chunk):
            if len(memo) > self.limit:
                for key in list(memo)[self.limit // 4 : 3 * self.limit // 4]:
                    del memo[key]
            rows, heads, holes = [], [], []
            for text in texts[at : at + chunk]:
                head, rest = self._cut(text)
                found = list(map(memo.get, rest))
                i = -1
                try:
                    while True:
                        i = found.index(None, i + 1)
                        holes.append((found, i, rest[i]))
                except ValueError:
                    pass
                rows.append(found)
                heads.append(head)
            todo = list(dict.fromkeys(x for *_, x in holes))
            memo.update(zip(todo, self.encode_many([lead + x for x in todo]), strict=True))
            for found, i, x in holes:
                found[i] = memo[x]
            first = iter(self.encode_many([head for head in heads if head is not None]))
            for head, found in zip(heads, rows, strict=True):
                yield found if head is None else [next(first), *found]
