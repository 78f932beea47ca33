"""Token ids of the public byte-level vocabulary.

``tiktoken`` holds the same vocabulary and pattern as the ``tokenizers`` file
and gives the same ids several times faster; texts that spell a special token
are left to ``tokenizers`` itself.
"""

from __future__ import annotations

import base64

import numpy as np
import public_tokenizers

#: The vocabulary files and the special token of the former.
JSON, RANKS, SPECIAL = "byte_bpe_50k.json", "byte_bpe_50k.tiktoken", "<|endoftext|>"
END = 0


class Encoder:
    """Ids of texts; ``folder`` overrides where the vocabulary files lie."""

    def __init__(self, folder: str | None = None):
        import tiktoken

        self._path = (lambda name: f"{folder}/{name}") if folder else public_tokenizers.path
        with open(self._path(RANKS), "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        self._fast = tiktoken.Encoding("byte_bpe_50k", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self._slow = None

    def ids(self, text: str) -> np.ndarray:
        """The ids of one text, without special tokens of the tokenizer's own."""
        if SPECIAL not in text:
            return np.asarray(self._fast.encode_to_numpy(text, disallowed_special=()), "<u4")
        if self._slow is None:
            from tokenizers import Tokenizer

            self._slow = Tokenizer.from_file(self._path(JSON))
        return np.array(self._slow.encode(text, add_special_tokens=False).ids, "<u4")


_HELD: dict[str | None, Encoder] = {}


def encoder(folder: str | None = None) -> Encoder:
    """One encoder for each worker process and folder."""
    if folder not in _HELD:
        _HELD[folder] = Encoder(folder)
    return _HELD[folder]
