"""Words of a text as the classifier, the search index and the license scan see them."""

from __future__ import annotations

#: Fixed table for bytes.translate: ASCII letters, digits and bytes beyond ASCII stay, all else becomes a space.
PLAIN = bytes(32 if i < 48 or 57 < i < 65 or 90 < i < 97 or 122 < i < 128 else i for i in range(256))
