"""Token ids of whole texts by a public byte-level tokenizer, with a cache of the pieces between spaces.

The pre-tokenizer of the vocabulary always cuts before a single space that stands between two
characters that aren't white space, and on both sides of a line end that does. So the ids of a text are those of its parts at such places, and
parts repeat. Parts next to other white space stay together with it.
"""

from __future__ import annotations

import os
from array import array

MARKS = ".,;:!?"

#: Byte-level vocabularies write a byte as a character: itself if it shows, else the next free one from 256 on.
_hidden = [b for b in range(256) if not (33 <= b <= 126 or 161 <= b <= 172 or b >= 174)]
SHOWN = {b: 256 + i for i, b in enumerate(_hidden)}

_open: dict = {}

#: Caches of a worker, kept from task to task; each is bounded.
_caches: dict = {}


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def tokenizer(path: str):
    if path not in _open:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        _open[path] = Tokenizer.from_file(path)
    return _open[path]


class _Parts(dict):
    """Ids of " part", or of "\\npart" for one that begins with a line end, as bytes; None for a part that white space touches.

    When full it starts anew, and what is still asked for comes over from the full one.
    """

    def __init__(self, encode, most: int):
        super().__init__()
        self.encode, self.most = encode, most
        self.line_end, self.old = encode("\n", ""), {}

    def __missing__(self, part: str) -> bytes | None:
        out = self.old.get(part)
        if out is None:
            line = part[:1] == "\n"
            body = part[1:] if line else part
            if not body or body[0].isspace() or body[-1].isspace():
                return None
            out = self.line_end + self.encode(body, "") if line else self.encode(part, " ")
        if len(part) <= 64:
            if len(self) >= self.most:
                self.old = dict(self)
                self.clear()
            self[part] = out
        return out


class Encoder:
    """Text to ids as little-endian unsigned 32-bit integers, as bytes."""

    def __init__(self, path: str | None = None, most: int = 500_000):
        self.plain = tokenizer(path or default_vocabulary())
        self.model = self.plain.model if self.plain.normalizer is None else None
        self.marks: dict[str, bytes] = {}
        self.parts: dict = {}
        self.parts = _caches.setdefault((path, most), _Parts(self._part, most))
        # Special strings cross spaces only if one of them holds a space; then nothing is cut.
        added = self.plain.get_added_tokens_decoder().values()
        self.whole = any(" " in t.content or t.lstrip or t.rstrip for t in added)

    def _part(self, part: str, before: str) -> bytes:
        """Ids of ``before`` and a part. Letters alone are one unit of the pre-tokenizer, marks after them the next."""
        word = part.rstrip(MARKS)
        if self.model is None or not word.isalpha():
            return self._direct(before + part)
        # The word without its marks may be known already.
        out = self.parts.get(word) if before and len(word) < len(part) else None
        if out is None:
            if word.isascii():
                shown = "\u0120" + word if before else word
            else:
                shown = (before + word).encode().decode("latin-1").translate(SHOWN)
            out = array("I", [t.id for t in self.model.tokenize(shown)]).tobytes()
        if len(word) == len(part):
            return out
        tail = part[len(word) :]
        if tail not in self.marks:
            if len(self.marks) > 10_000:
                self.marks.clear()
            self.marks[tail] = self._direct(tail)
        return out + self.marks[tail]

    def _direct(self, text: str) -> bytes:
        return array("I", self.plain.encode(text, add_special_tokens=False).ids).tobytes()

    def encode(self, text: str | None) -> bytes:
        if not text:
            return b""
        if self.whole:
            return self._direct(text)
        parts = text.replace("\n", " \n").split(" ")
        if parts[0] and not parts[0][-1].isspace():
            try:
                return self._direct(parts[0]) + b"".join(map(self.parts.__getitem__, parts[1:]))
            except TypeError:  # a part without ids of its own
                pass
        parts = text.split(" ")
        ids = [self.parts[p] if "\n" not in p else None for p in parts[1:]]
        out, start = [], 0
        for k in range(1, len(parts) + 1):
            # A cut before part k needs both neighbours clean.
            if k == len(parts) or (parts[k] and not parts[k][0].isspace() and parts[k - 1] and not parts[k - 1][-1].isspace()):
                run = " ".join(parts[start:k])
                out.append((ids[start - 1] if start and k == start + 1 and ids[start - 1] is not None else None) or self._direct((" " if start else "") + run))
                start = k
        return b"".join(out)
