"""Exact tokenizer front end that encodes each distinct piece of text once."""

from __future__ import annotations

import json
import os
import re

import numpy as np

#: The normalizer and splitter for which texts may be taken apart at blanks. Fixed values.
NORMALIZERS = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]
SPLIT = "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"

#: Chunks of printable ASCII and Latin-1 letters, which no normal form changes, and their pieces by the same splitter.
PLAIN = re.compile(r"[!-~À-ÖØ-öø-ÿ]{1,64}")
PIECE = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^a-z0-9ß-öø-ÿ]+")


#: Stand-ins of bytes in a byte-level vocabulary: printable ones stand for themselves, the others for 256 and on.
_ITSELF = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
_OTHERS = [b for b in range(256) if b not in set(_ITSELF)]
STAND_IN = {b: chr(b) for b in _ITSELF} | {b: chr(256 + k) for k, b in enumerate(_OTHERS)}


class Kept(dict):
    """A map that makes what it lacks, with at most twice ``limit`` entries: what was not asked for while ``limit`` new
    ones came is forgotten. What ``make`` says not to keep is made again each time."""

    def __init__(self, make, limit: int):
        super().__init__()
        self.make, self.limit, self.old = make, limit, {}

    def __missing__(self, key: str) -> bytes:
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
            if len(key) > 64:
                return value
        if len(self) >= self.limit:
            self.old.clear()  # first, so that no third generation takes memory meanwhile
            self.old.update(self)
            self.clear()
        self[key] = value
        return value


class ChunkTokenizer:
    """Encodes whole texts with a ``tokenizers`` file; ids as little-endian unsigned 32-bit bytes.

    A tokenizer that drops blanks and splits as ``SPLIT`` does never joins across blanks or pieces, so a text's ids are
    those of its chunks between blanks, and a plain chunk's are those of its pieces, in order. Both repeat far more often
    than texts do and are kept, in bounded number; results do not depend on what is kept. Chunks with other characters
    are encoded as they stand, and with any other tokenizer file whole texts are. tests/llm hold this against the library.
    """

    def __init__(self, path: str, limit: int = 300_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.engine = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            made = json.load(f)
        normal, splits = made.get("normalizer") or {}, (made.get("pre_tokenizer") or {}).get("pretokenizers") or [{}]
        self.by_chunk = (
            normal.get("normalizers") == NORMALIZERS and splits[0].get("pattern") == {"Regex": SPLIT} and bool(splits[0].get("invert"))
            and [x["type"] for x in splits[1:]] == ["ByteLevel"] and not splits[1]["add_prefix_space"] and not made.get("post_processor")
        )
        self.special = [t["content"] for t in made.get("added_tokens", [])]
        top = max(self.engine.get_vocab().values(), default=0) + 1
        self.id_bytes = [i.to_bytes(4, "little") for i in range(top)] if self.by_chunk else []
        self.words = self.engine.model.tokenize
        self.chunks, self.pieces = Kept(self._chunk, limit), Kept(self._piece, limit * 2 // 3)

    def _plainly(self, items: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.engine.encode_batch_fast(items, add_special_tokens=False)]

    def _piece(self, piece: str) -> bytes:
        if not piece.isascii():
            piece = "".join([STAND_IN[b] for b in piece.encode()])
        table = self.id_bytes
        return b"".join([table[t.id] for t in self.words(piece)])

    def _chunk(self, chunk: str) -> bytes:
        if chunk.isascii() and chunk.isalpha():
            return self.pieces[chunk.lower()]
        if not chunk:
            return b""
        if not PLAIN.fullmatch(chunk) or ("<|" in chunk and any(s in chunk for s in self.special)):
            return self._plainly([chunk])[0]
        pieces = PIECE.findall(chunk.lower())
        return self.pieces[pieces[0]] if len(pieces) == 1 else b"".join([self.pieces[p] for p in pieces])

    def encode(self, text: str) -> bytes:
        if not self.by_chunk:
            return self._plainly([text])[0]
        return b"".join(map(self.chunks.__getitem__, text.replace("\n", " ").split(" ")))

    def encode_all(self, texts: list[str]) -> list[bytes]:
        return [self.encode(t) for t in texts] if self.by_chunk else self._plainly(texts)


_engines: dict[str, ChunkTokenizer] = {}


def tokenizer(path: str) -> ChunkTokenizer:
    """One tokenizer for each file and Python worker."""
    if path not in _engines:
        _engines[path] = ChunkTokenizer(path)
    return _engines[path]


def public_path(name: str = "word_bpe_49k.json") -> str:
    """Place of a public vocabulary file; it is read where it is installed, never copied."""
    import public_tokenizers

    return public_tokenizers.path(name)
