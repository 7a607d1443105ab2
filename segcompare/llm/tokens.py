"""Token ids of public tokenizers, the same in every worker.

The byte-level vocabulary is run by tiktoken where all characters are below U+0100, which is faster and
was compared with tokenizers on random texts; any other text goes to tokenizers itself.
"""

from __future__ import annotations

import base64
import os

DEFAULT = "byte_bpe_50k.json"
SPECIAL = "<|endoftext|>"
SPECIAL_ID = 50256


class ByteTokenizer:
    """encode(text): the ids that tokenizers gives without added special tokens; `ordinary` reads SPECIAL as plain text."""

    def __init__(self, path: str | None = None, ranks_path: str | None = None):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        import public_tokenizers
        import tiktoken

        self.path = path or public_tokenizers.path(DEFAULT)
        ranks_path = ranks_path or self.path.removesuffix(".json") + ".tiktoken"
        with open(ranks_path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.fast = tiktoken.Encoding("fast", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self._slow = None

    def slow(self):
        if self._slow is None:
            from tokenizers import Tokenizer

            self._slow = Tokenizer.from_file(self.path)
        return self._slow

    def encode(self, text: str, ordinary: bool = False) -> list[int]:
        try:
            text.encode("latin-1")
        except UnicodeEncodeError:
            tokenizer = self.slow()
            tokenizer.encode_special_tokens = ordinary
            return tokenizer.encode(text, add_special_tokens=False).ids
        if ordinary or SPECIAL not in text:
            return self.fast.encode_ordinary(text)
        out: list[int] = []
        for k, part in enumerate(text.split(SPECIAL)):
            if k:
                out.append(SPECIAL_ID)
            out += self.fast.encode_ordinary(part)
        return out


_cached: dict[str | None, ByteTokenizer] = {}


def tokenizer(path: str | None = None) -> ByteTokenizer:
    """The worker's own instance."""
    if path not in _cached:
        _cached[path] = ByteTokenizer(path)
    return _cached[path]
