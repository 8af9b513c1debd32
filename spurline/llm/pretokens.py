"""What the tokenizing operators share: where texts may be cut, and a memory of bounded size."""

from __future__ import annotations

import re

#: A space that does not stand before a visible character. Texts without one may be cut before each space, if they are split
#: by the public pattern: there a space before a visible character always starts a new pre-token.
LOOSE_SPACE = re.compile(r" (?=\s|$)")


def cuts_at_spaces(pattern: str) -> bool:
    """Whether texts split by ``pattern`` may be cut before spaces: known of the public pattern only."""
    import public_tokenizers

    return pattern == public_tokenizers.PATTERN


class Memo(dict):
    """Remembers values of strings until they take ``room`` bytes or so; later ones are worked out anew each time."""

    def __init__(self, room: int):
        super().__init__()
        self.room = room

    def keep(self, key: str, value):
        size = 200 + 2 * len(key) + (len(value) if isinstance(value, bytes) else 0)
        if size <= self.room:
            self.room -= size
            self[key] = value
        return value
