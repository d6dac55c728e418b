"""Token ids of a public byte-level BPE vocabulary."""

from __future__ import annotations

import base64

import numpy as np

#: Fixed value: the special token of the vocabulary and its id.
SPECIAL = {"<|endoftext|>": 50256}


class Encoder:
    """encode(text) -> little-endian uint32 ids. Strings of `special` tokens become their ids; without any, all text is ordinary text."""

    def __init__(self, ranks_file: str, pattern: str, special: dict[str, int] | None = None):
        import tiktoken

        with open(ranks_file, "rb") as lines:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        own = tiktoken.Encoding("byte-bpe", pat_str=pattern, mergeable_ranks=ranks, special_tokens=special or {})
        self.special, self.plain, self.whole = tuple(special or ()), own.encode_ordinary, own.encode

    def encode(self, text: str | None) -> np.ndarray:
        if not text:
            return np.empty(0, dtype="<u4")
        marked = any(s in text for s in self.special)
        return np.array(self.whole(text, allowed_special="all") if marked else self.plain(text), dtype="<u4")


_ENCODERS: dict[tuple, Encoder] = {}


def encoder(ranks_file: str | None = None, pattern: str | None = None, special: dict[str, int] | None = None) -> Encoder:
    """The worker's encoder; by default of the public 50k vocabulary, whose files stay where they are installed."""
    if ranks_file is None:
        import public_tokenizers

        ranks_file, pattern = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN
    key = (ranks_file, pattern, tuple(sorted((special or {}).items())))
    if key not in _ENCODERS:
        _ENCODERS[key] = Encoder(ranks_file, pattern, special)
    return _ENCODERS[key]
