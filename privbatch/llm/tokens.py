"""Token ids of whole texts by a public tokenizer file, with bounded caches.

The tokenizer lower-cases, drops white space, cuts what is left into runs (contractions, letters,
single digits, other symbols) and merges inside a run only.  So the ids of a text are those of
its white-space chunks, and those of a chunk are its runs'.  Chunks and runs repeat far more
often than texts; both are cached, and only an unseen run goes through the merges.

This holds for texts of plain characters (ASCII and Latin-1 letters and signs), where Python and
the tokenizer agree on letters, case and white space.  Any other text is encoded whole.
"""

from __future__ import annotations

import re
from array import array

CACHE_CHUNKS = 400_000
CACHED_CHARS = 64
_PLAIN = re.compile(r"[\t\n\r -~\xa0\xa1-\xa9\xab\xac\xae-\xb1\xb4\xb6-\xb8\xbb\xbf-\xff]*")
#: The runs of a lower-cased chunk; fixed by the tokenizer's own pattern.
_RUN = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^\sa-zß-öø-ÿ0-9]+")


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def _byte_letters() -> list[str]:
    """The character that stands for each byte in a byte-level vocabulary: itself where it is visible, else the next free one from 256."""
    visible = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
    hidden = [b for b in range(256) if b not in visible]
    return [chr(b) if b in visible else chr(256 + hidden.index(b)) for b in range(256)]


_LETTER = _byte_letters()


class Encoder:
    """Encodes texts to little-endian unsigned 32-bit ids, ``end_id`` appended to each."""

    held: dict[tuple[str, int], Encoder] = {}

    def __init__(self, path: str, end_id: int):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.merge = self.tokenizer.model.tokenize
        self.end = array("I", [end_id]).tobytes()
        self.chunks: dict[str, bytes] = {}
        self.runs: dict[str, bytes] = {}

    @classmethod
    def of(cls, path: str, end_id: int) -> Encoder:
        """The encoder of this Python worker."""
        if (path, end_id) not in cls.held:
            cls.held[path, end_id] = cls(path, end_id)
        return cls.held[path, end_id]

    def _run(self, run: str) -> bytes:
        ids = array("I", [t.id for t in self.merge(run if run.isascii() else "".join([_LETTER[b] for b in run.encode()]))]).tobytes()
        if len(run) <= CACHED_CHARS:
            if len(self.runs) >= CACHE_CHUNKS:
                self.runs.clear()
            self.runs[run] = ids
        return ids

    def _chunk(self, chunk: str) -> bytes:
        runs = self.runs
        ids = b"".join([runs.get(r) or self._run(r) for r in _RUN.findall(chunk)])
        if len(chunk) <= CACHED_CHARS:
            if len(self.chunks) >= CACHE_CHUNKS:
                self.chunks.clear()
            self.chunks[chunk] = ids
        return ids

    def __call__(self, text: str | None) -> bytes:
        if not text:
            return self.end
        if "<|" in text or not _PLAIN.fullmatch(text):
            return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes() + self.end
        get = self.chunks.get
        return b"".join([get(c) or self._chunk(c) for c in text.lower().split()]) + self.end
