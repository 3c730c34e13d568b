"""A bounded memo of encoded pieces."""

from __future__ import annotations

from collections.abc import Callable


class PieceCache(dict):
    """piece -> encoded bytes, filled on first use.

    Once ``limit`` pieces are held they become the old generation and a new one begins; pieces met again move over, the
    others go with the next change.  So at most twice the limit is held and frequent pieces stay.  Long pieces are encoded
    each time.
    """

    def __init__(self, encode: Callable[[str], bytes], limit: int, longest: int = 40) -> None:
        super().__init__()
        self.encode, self.limit, self.longest, self.old = encode, limit, longest, {}

    def __missing__(self, piece: str) -> bytes:
        value = self.old.get(piece)
        if value is None:
            value = self.encode(piece)
            if len(piece) > self.longest:
                return value
        if len(self) >= self.limit:
            self.old = dict(self)
            self.clear()
        self[piece] = value
        return value
