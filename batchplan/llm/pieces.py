"""Token ids of text pieces, kept in one flat array so that a document's ids are a gather."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Sequence

import numpy as np

#: Pieces that a Python worker remembers at most; then it forgets all of them and starts anew.
MEMORY = 400_000


class _Numbers(dict):
    """piece -> its number; a piece that is new gets the next one, so that each piece is looked up once."""

    def __init__(self) -> None:
        self.new: list[str] = []

    def __missing__(self, piece: str) -> int:
        self[piece] = n = len(self)
        self.new.append(piece)
        return n


class PieceStore:
    """piece -> token ids, filled by ``encode`` for the pieces that are new."""

    def __init__(self, encode: Callable[[Sequence[str]], tuple[np.ndarray, np.ndarray]], memory: int = MEMORY) -> None:
        self.encode, self.memory = encode, memory
        self.clear()

    def clear(self) -> None:
        self.index = _Numbers()
        self.flat = np.zeros(1 << 16, np.uint32)
        self.used = 0
        self.starts = np.zeros(1 << 14, np.int64)
        self.lens = np.zeros(1 << 14, np.int64)

    def _grown(self, a: np.ndarray, n: int) -> np.ndarray:
        return a if n <= len(a) else np.concatenate([a, np.zeros(max(n, 2 * len(a)) - len(a), a.dtype)])

    def numbers(self, pieces: Sequence[str]) -> np.ndarray:
        """The pieces' numbers; ``learn`` is to be called before their ids are taken."""
        return np.fromiter(map(self.index.__getitem__, pieces), np.int64, len(pieces))

    def learn(self) -> None:
        """Encodes the pieces that are new."""
        if not self.index.new:
            return
        new, self.index.new = self.index.new, []
        try:
            ids, lens = self.encode(new)
        except BaseException:
            self.clear()  # numbers without ids are of no use
            raise
        n, k = self.used, len(self.index) - len(new)
        self.flat = self._grown(self.flat, n + len(ids))
        self.flat[n : n + len(ids)] = ids
        self.starts, self.lens = self._grown(self.starts, k + len(new)), self._grown(self.lens, k + len(new))
        self.starts[k : k + len(new)] = n + np.cumsum(lens) - lens
        self.lens[k : k + len(new)] = lens
        self.used = n + len(ids)

    def ids(self, pieces: Sequence[str]) -> np.ndarray:
        """The pieces' ids, one after another."""
        return self.ids_and_lens(pieces)[0]

    def ids_and_lens(self, pieces: Sequence[str]) -> tuple[np.ndarray, np.ndarray]:
        """The pieces' ids, one after another, and each piece's number of them."""
        which = self.numbers(pieces)
        self.learn()
        return self.taken(which)

    def taken(self, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The same for the pieces' numbers."""
        lens = self.lens[which]
        total = int(lens.sum())
        at = np.repeat(self.starts[which] - (np.cumsum(lens) - lens), lens) + np.arange(total)
        return self.flat[at], lens

    def room(self) -> None:
        """Called between documents: forget if memory is used up."""
        if len(self.index) > self.memory:
            self.clear()


def stretches(text: str, limit: int, split: Callable[[str, int], int]) -> Iterable[str]:
    """text in stretches of about ``limit`` characters, each ending where ``split`` allows."""
    at = 0
    while len(text) - at > limit:
        end = split(text, at + limit)
        if end <= at or end >= len(text):
            break
        yield text[at:end]
        at = end
    yield text[at:] if at else text
