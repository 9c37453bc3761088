"""A bounded table of distinct text chunks and what an encoder makes of them."""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

#: Entries after which a worker's table starts anew; it bounds memory, results do not depend on it.
MOST_CHUNKS = 700_000
#: Chunks longer than this are encoded each time and not kept, so that the table's bytes are bounded too.
LONGEST = 256
#: Characters of text whose unknown chunks are encoded in one call.
GROUP_CHARS = 1 << 18
_WORD = re.compile(r"[^\x20\x09-\x0D]+")


class ChunkTable:
    """Encodes each distinct chunk once and joins the results back by position."""

    def __init__(self, encode: Callable[[list[str]], list], most: int = MOST_CHUNKS):
        self._encode, self._most, self._known = encode, most, {}

    def of_all(self, texts: list[list[str]]) -> list[list]:
        """For the chunks of several texts, what was made of each."""
        known = self._known
        out = [list(map(known.get, t)) for t in texts]
        short = [(t, x) for t, x in zip(texts, out, strict=True) if None in x]
        if short:
            new = list({c for t, x in short for c, y in zip(t, x, strict=True) if y is None})
            made = dict(zip(new, self._encode(new), strict=True))
            for t, x in short:
                x[:] = [made[c] if y is None else y for c, y in zip(t, x, strict=True)]
            if len(known) + len(new) > self._most:
                known.clear()
            known.update((c, x) for c, x in made.items() if len(c) <= LONGEST)
        return out

    def of_texts(self, texts: list[str | None], cut: Callable[[str], list[str]] = _WORD.findall) -> Iterator[list]:
        """The same for whole texts (None: empty), in groups of bounded size, in order."""
        group, size = [], 0
        for t in texts:
            group.append(cut(t) if t else [])
            size += len(t or "")
            if size >= GROUP_CHARS:
                yield from self.of_all(group)
                group, size = [], 0
        if group:
            yield from self.of_all(group)
