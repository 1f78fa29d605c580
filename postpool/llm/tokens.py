"""Tokenizers as parameters: a vocabulary file's path, opened once in each Python worker.

``encode`` gives a text's ids as little-endian unsigned 32-bit integers in bytes. A null text counts as empty.
"""

from __future__ import annotations

import base64
import json
import re
import struct
from functools import lru_cache

#: Chunks of text remembered with their ids in one worker; beyond it the memory starts afresh.
REMEMBERED = 400_000


@lru_cache(maxsize=4)
def ranked(path: str, pattern: str):
    """A tiktoken encoding of a file of ranks."""
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


class ChunkEncoder:
    """A `tokenizers` file whose pre-tokens hold no white space; each different pre-token is encoded once a worker.

    Texts of Latin letters (below U+0250, of one normal form) are lower-cased and split into pre-tokens here. Any other
    text is cut at blanks and line feeds, which no pre-token crosses, and texts that hold a special token are encoded
    whole. All three ways give the ids of the whole text; tests hold them against the tokenizer itself.
    """

    #: The split pattern of the lower-casing vocabulary (a fixed value of its file); other files use the second way.
    PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
    LETTERS, DIGITS = "a-zªµºß-öø-ɏ", "0-9²³¹¼½¾"

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.cut = re.compile(r"[ \n]+")
        self.known: dict[str, bytes] = {}
        self.parts: dict[str, bytes] = {}
        with open(path, encoding="utf-8") as f:
            parts = json.load(f)
        split = ((parts.get("pre_tokenizer") or {}).get("pretokenizers") or [{}])[0]
        steps = [n.get("type") for n in (parts.get("normalizer") or {}).get("normalizers") or []]
        self.latin = split.get("pattern", {}).get("Regex") == self.PATTERN and steps == ["NFC", "Replace", "Lowercase"]
        self.foreign = re.compile("[^\t\n\r\x20-\x7e\xa1-\u024f]")
        self.pretoken = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{self.LETTERS}]+|[{self.DIGITS}]|[^\\s{self.LETTERS}{self.DIGITS}]+")

    def whole(self, text: str) -> bytes:
        ids = self.tokenizer.encode(text, add_special_tokens=False).ids
        return struct.pack(f"<{len(ids)}I", *ids)

    def learn(self, known: dict[str, bytes], chunks: list[str]) -> bytes:
        """The ids of chunks, new ones among them."""
        if len(known) > REMEMBERED:
            known.clear()
        new = list({c for c in chunks if c not in known})
        plain = [c for c in new if known is self.parts and c.isascii() and c.isalpha()]
        tokenize = self.tokenizer.model.tokenize  # a lower-case ASCII word is its own byte-level form
        for c in plain:
            ids = [t.id for t in tokenize(c)]
            known[c] = struct.pack(f"<{len(ids)}I", *ids)
        rest = [c for c in new if c not in known]
        for c, e in zip(rest, self.tokenizer.encode_batch_fast(rest, add_special_tokens=False)):
            known[c] = struct.pack(f"<{len(e.ids)}I", *e.ids)
        return b"".join([known[c] for c in chunks])

    def encode(self, text: str | None) -> bytes:
        if not text:
            return b""
        if any(s in text for s in self.special):
            return self.whole(text)
        if self.latin and not self.foreign.search(text):
            known, chunks = self.parts, self.pretoken.findall(text.lower())
        else:
            known, chunks = self.known, self.cut.split(text)
        try:
            return b"".join([known[c] for c in chunks])
        except KeyError:
            return self.learn(known, chunks)


@lru_cache(maxsize=4)
def chunked(path: str) -> ChunkEncoder:
    import os

    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    return ChunkEncoder(path)
