"""Token ids of a byte-level BPE vocabulary file, as little-endian unsigned 32-bit bytes."""

from __future__ import annotations

import json
from array import array

# Fixed value: the word pattern of the vocabulary, with possessive repeats.
_PATTERN = r"""'(?:[sdmt]|ll|ve|re)| ?\p{L}++| ?\p{N}++| ?[^\s\p{L}\p{N}]++|\s++$|\s+(?!\S)|\s"""


class TokenIds:
    """encode(text) -> four bytes for each id.  tokenizer_path: a tokenizers JSON file with a byte-level BPE model.

    The vocabulary is read from that file; the merging is done by tiktoken, which is four times as fast and agrees id for
    id.  Texts that hold a special token's string go through the tokenizers library itself.
    """

    def __init__(self, tokenizer_path: str):
        import tiktoken

        assert array("I").itemsize == 4
        self.path, self.library = tokenizer_path, None
        with open(tokenizer_path, encoding="utf-8") as f:
            spec = json.load(f)
        back = {c: b for b, c in _byte_letters().items()}
        self.special = [t["content"] for t in spec.get("added_tokens", [])]
        ranks = {bytes(map(back.__getitem__, piece)): i for piece, i in spec["model"]["vocab"].items() if piece not in self.special}
        self.plain = tiktoken.Encoding("ranks", pat_str=_PATTERN, mergeable_ranks=ranks, special_tokens={})._core_bpe.encode_ordinary

    def encode(self, text: str) -> bytes:
        if any(s in text for s in self.special):
            if self.library is None:  # large, and rarely needed
                from tokenizers import Tokenizer

                self.library = Tokenizer.from_file(self.path)
            return array("I", self.library.encode(text, add_special_tokens=False).ids).tobytes()
        return array("I", self.plain(text)).tobytes()


def _byte_letters() -> dict[int, str]:
    """The printable stand-in of each byte in byte-level vocabularies: itself if printable, else the next from 256 on."""
    keep = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    out, n = {b: chr(b) for b in keep}, 256
    for b in range(256):
        if b not in out:
            out[b], n = chr(n), n + 1
    return out
