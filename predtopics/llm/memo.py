"""A memo for the pieces that texts repeat, bounded in bytes."""

from __future__ import annotations

from collections.abc import Callable

#: Bytes that an entry takes besides its piece and value: two objects' headers and their place in the table.
ENTRY = 200
#: Pieces beyond this length are made anew each time: they hardly repeat.
LONG = 64


class Memo(dict):
    """piece -> value (both strings or bytes), filled on a miss.

    The two latest generations of pieces are held, each of at most half of ``limit`` bytes; a piece of the older one that is
    asked for again moves to the newer one.
    """

    def __init__(self, make: Callable, limit: int) -> None:
        super().__init__()
        self.make, self.half, self.used, self.old = make, limit // 2, 0, {}

    def __missing__(self, piece):  # noqa: ANN001, ANN204
        if len(piece) > LONG:
            return self.make(piece)
        value = self.old.get(piece)
        if value is None:
            value = self.make(piece)
        self._hold(ENTRY + len(piece) + len(value))
        self[piece] = value
        return value

    def fill(self, pieces: list, values: list) -> None:
        """Take new pieces, none beyond LONG, with the values made of them."""
        self._hold(ENTRY * len(pieces) + sum(map(len, pieces)) + sum(map(len, values)))
        self.update(zip(pieces, values))

    def _hold(self, size: int) -> None:
        self.used += size
        if self.used > self.half:
            self.old, self.used = dict(self), size
            self.clear()
