"""Encoding whole texts with a public tokenizer file, one encoding for each distinct chunk.

Both vocabularies never join characters across the step from a visible character to white
space, so a text is cut there and each distinct chunk is encoded once by the library; the ids
of a text are those of its chunks in order (tests compare with encoding the text as a whole by a
tokenizer as it is loaded). A text that holds an added token of the vocabulary, such as its end
mark, goes through the library as a whole, since added tokens are found before the text is split.

A null text has no ids and equal texts have equal ids; a text over 2^20 characters is cut piece by
piece, so its chunks are never held all at once.
"""

from __future__ import annotations

import json
import re
import unicodedata
from array import array

# Python counts 1C to 1F as white space, the tokenizers' patterns don't.
_CHUNK = re.compile(r"[^\S\x1c-\x1f]*[\S\x1c-\x1f]+|[^\S\x1c-\x1f]+")
_LONG = 1 << 20


# fixed value: the public pattern that byte-level vocabularies split texts by
BYTE_LEVEL_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Characters on which all Unicode versions agree, as do the normal forms.
_PLAIN = re.compile("[\t\n\r -~\u00a1-\u024f]*")


def plain_pattern(pattern: str) -> re.Pattern:
    """The vocabulary's pattern with letters and numbers spelled out, for plain texts only."""
    spelled = {}
    for kind in "LN":
        points = [i for i in range(0x250) if unicodedata.category(chr(i))[0] == kind and _PLAIN.fullmatch(chr(i))]
        runs = [i for i in points if i - 1 not in points]
        spelled[kind] = "".join(f"\\u{lo:04x}-\\u{next(i for i in range(lo, 0x251) if i + 1 not in points):04x}" for lo in runs)
    out, inside, i = [], False, 0
    while i < len(pattern):
        if pattern.startswith(("\\p{L}", "\\p{N}"), i):
            runs = spelled[pattern[i + 3]]
            out.append(runs if inside else f"[{runs}]")
            i += 5
            continue
        step = 2 if pattern[i] == "\\" else 1
        inside = pattern[i] == "[" or inside and pattern[i] != "]"
        out.append(pattern[i : i + step])
        i += step
    return re.compile("".join(out))


def byte_letters() -> str:
    """The letter for each byte: printable bytes stand for themselves, the others follow from 256."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return "".join(chr(b if b in own else next(spare)) for b in range(256))


class ChunkEncoder:
    """Little-endian unsigned 32-bit ids of texts; its memory holds about `room` entries at most.

    A plain text is split by the vocabulary's own pattern and each distinct piece goes once to
    the library's merge model. Any other text is cut into chunks at white space, and each
    distinct chunk goes through the library's whole chain.
    """

    def __init__(self, path: str, room: int = 800_000):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_padding()
        self.tokenizer.no_truncation()
        if hasattr(self.tokenizer.model, "_resize_cache"):
            self.tokenizer.model._resize_cache(0)  # the memories below do its work
        self.room = room
        self.known: dict[str, bytes] = {}  # of chunks
        self.pieces: dict[str, bytes] = {}
        spec = json.loads(self.tokenizer.to_str())
        # in any case, since some are looked for in the normal form
        added = [re.escape(t["content"]) for t in spec["added_tokens"] if t["content"]]
        self.added = re.compile("|".join(added), re.IGNORECASE).search if added else lambda text: None
        steps = lambda x, key: [] if not x else x[key] if x["type"] == "Sequence" else [x]
        pre, norm = steps(spec["pre_tokenizer"], "pretokenizers"), steps(spec["normalizer"], "normalizers")
        self.lower = any(x["type"] == "Lowercase" for x in norm)
        pattern = None
        if [x["type"] for x in pre] == ["ByteLevel"] and pre[0]["use_regex"] and not pre[0]["add_prefix_space"] and not norm:
            pattern = BYTE_LEVEL_PATTERN
        elif [x["type"] for x in pre] == ["Split", "ByteLevel"] and pre[0]["behavior"] == "Removed" and pre[0]["invert"] and not pre[1]["use_regex"] and {x["type"] for x in norm} <= {"NFC", "Replace", "Lowercase"}:
            pattern = pre[0]["pattern"]["Regex"]
        self.split = pattern and plain_pattern(pattern).findall
        self.letters = byte_letters()

    def _learn_pieces(self, pieces: set[str]) -> None:
        new = pieces - self.pieces.keys()
        if len(new) + len(self.pieces) > self.room:
            self.pieces = {}
            new = pieces
        known, letters, merge = self.pieces, self.letters, self.tokenizer.model.tokenize
        for p in new:
            # a visible ASCII character stands for its own byte
            shown = p if p.isascii() and p.isalnum() else letters[32] + p[1:] if p[0] == " " and p[1:].isascii() and p[1:].isalnum() else p.encode().decode("latin-1").translate(letters)
            known[p] = array("I", [t.id for t in merge(shown)]).tobytes()

    def _learn(self, chunks: set[str]) -> None:
        new = chunks - self.known.keys()
        if len(new) + len(self.known) > self.room:
            self.known = {}
            new = chunks
        new = list(new)
        for i in range(0, len(new), 2000):
            part = new[i : i + 2000]
            for c, e in zip(part, self.tokenizer.encode_batch_fast(part, add_special_tokens=False)):
                self.known[c] = array("I", e.ids).tobytes()

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """The ids of each text; a null text has none."""
        out, cut, split = [b""] * len(texts), {}, {}
        for i, t in enumerate(texts):
            if t and self.added(t):
                out[i] = array("I", self.tokenizer.encode(t, add_special_tokens=False).ids).tobytes()
            elif t and len(t) > _LONG:
                out[i] = self._long(t)
            elif t and self.split and _PLAIN.fullmatch(t):
                split[i] = self.split(t.lower() if self.lower else t)
            elif t:
                cut[i] = _CHUNK.findall(t)
        for parts, learn, name in ((split, self._learn_pieces, "pieces"), (cut, self._learn, "known")):
            learn({c for found in parts.values() for c in found})
            at = getattr(self, name).__getitem__
            for i, found in parts.items():
                out[i] = b"".join(map(at, found))
        return out

    def _long(self, text: str) -> bytes:
        out, batch = [], []

        def flush():
            self._learn(set(batch))
            out.extend(map(self.known.__getitem__, batch))
            batch.clear()

        for m in _CHUNK.finditer(text):
            batch.append(m[0])
            if len(batch) >= 100_000:
                flush()
        flush()
        return b"".join(out)


_ENCODERS: dict[str, ChunkEncoder] = {}


def encoder(path: str, room: int = 800_000) -> ChunkEncoder:
    """One encoder for each worker process and vocabulary file."""
    from .common import take_over

    take_over(f"encoder {path}", _ENCODERS.clear)
    if path not in _ENCODERS:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        _ENCODERS[path] = ChunkEncoder(path, room)
    return _ENCODERS[path]


def groups(texts: list[str | None], most: int = 1 << 21):
    """Index ranges of neighbouring texts of about `most` characters in all."""
    lo, chars = 0, 0
    for i, t in enumerate(texts):
        chars += len(t) if t else 0
        if chars >= most:
            yield lo, i + 1
            lo, chars = i + 1, 0
    if lo < len(texts):
        yield lo, len(texts)


def vocabulary(name: str) -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))
