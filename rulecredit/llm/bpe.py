"""Exact byte-level BPE encoding for Spark workers.

:class:`ExactEncoder` returns, for a whole text, the ids of ``tokenizers`` as
little-endian unsigned 32-bit bytes. The byte-level scheme never merges across
pre-token borders, so a text's ids are its pre-tokens' ids in a row; pre-tokens
repeat a lot, so each worker keeps a bounded memo from pre-token to ids. Where a text has
characters whose class could differ between Unicode versions, the library splits it.
Texts that hold a special token's string go to the library whole.

``load`` checks the tokenizer file against the fast path's assumptions (byte-level
pre-tokenizer with the usual pattern, merges in id order, no normaliser); with any
other file every text goes to the library.
"""

from __future__ import annotations

import base64
import hashlib
import json
import re
from functools import lru_cache

import numpy as np

DEFAULT_FILE = "byte_bpe_50k.json"

#: Character classes of code points up to U+024F, where every Unicode version agrees.
LETTERS = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-ɏ"
NUMBERS = "0-9\xb2\xb3\xb9\xbc-\xbe"
BLANKS = "\t-\r \x85\xa0"
#: Also safe: common punctuation beyond that range (dashes, quotes, bullet, ellipsis, euro sign).
PUNCTUATION = "‐-‧‰-›€™"
SAFE = re.compile(f"[\x00-ɏ{PUNCTUATION}]*")
SPLIT = re.compile(
    f"'(?:[stmd]|re|ve|ll)| ?[{LETTERS}]+| ?[{NUMBERS}]+| ?[^{BLANKS}{LETTERS}{NUMBERS}]+|[{BLANKS}]+(?![^{BLANKS}])|[{BLANKS}]+"
)
MEMO_ENTRIES = 200_000


def byte_alphabet() -> dict[str, int]:
    """The printable stand-ins of byte-level vocabularies, as character -> byte."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    shifted = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(shifted)}


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(DEFAULT_FILE)


class _Memo(dict):
    """pre-token -> id bytes; emptied when full, so memory is bounded."""

    def __init__(self, encode_piece):
        super().__init__()
        self._encode = encode_piece

    def __missing__(self, piece: str) -> bytes:
        if len(self) >= MEMO_ENTRIES:
            self.clear()
        out = np.array(self._encode(piece), dtype="<u4").tobytes()
        if len(piece) <= 64:
            self[piece] = out
        return out


class ExactEncoder:
    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.special = [t["content"] for t in spec.get("added_tokens", [])]
        self.memo = None
        ranks = self._fast_ranks(spec)
        alphabet = byte_alphabet()
        size = self.library.get_vocab_size()
        self.pieces: list[bytes] = [b""] * size
        for token, i in self.library.get_vocab().items():
            known = all(c in alphabet for c in token) and token not in self.special
            self.pieces[i] = bytes(alphabet[c] for c in token) if known else token.encode()
        if ranks is not None:
            import tiktoken

            core = tiktoken.Encoding("memo", pat_str=r"[\s\S]+", mergeable_ranks=ranks, special_tokens={})
            self.memo = _Memo(core.encode_ordinary)

    def _fast_ranks(self, spec: dict) -> dict[bytes, int] | None:
        pre, model = spec.get("pre_tokenizer") or {}, spec["model"]
        plain = (
            spec.get("normalizer") is None
            and pre.get("type") == "ByteLevel"
            and not pre.get("add_prefix_space")
            and pre.get("use_regex", True)
            and model.get("type", "BPE") == "BPE"
            and not model.get("dropout")
            and not model.get("ignore_merges")
        )
        if not plain:
            return None
        alphabet, vocab = byte_alphabet(), model["vocab"]
        last = -1
        for m in model["merges"]:
            left, right = m if isinstance(m, list) else m.split(" ")
            rank = vocab.get(left + right, -1)
            if rank <= last:
                return None
            last = rank
        special = set(self.special)
        words = {t: i for t, i in vocab.items() if t not in special}
        if any(c not in alphabet for t in words for c in t):
            return None
        return {bytes(alphabet[c] for c in t): i for t, i in words.items()}

    def in_pieces(self, text: str) -> bool:
        """Whether the text's ids are its pre-tokens' ids in a row."""
        return self.memo is not None and not any(s in text for s in self.special)

    def split(self, text: str) -> list[str]:
        """The text's pre-tokens, in order."""
        if SAFE.fullmatch(text):
            return SPLIT.findall(text)
        return [text[a:b] for _, (a, b) in self.library.pre_tokenizer.pre_tokenize_str(text)]

    def encode(self, text: str) -> bytes:
        """Ids of a whole text as little-endian uint32 bytes."""
        if self.in_pieces(text):
            memo = self.memo
            return b"".join(map(memo.__getitem__, self.split(text)))
        return np.array(self.library.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def decode(self, ids: np.ndarray) -> str:
        """``decode(ids, skip_special_tokens=False)`` of a byte-level decoder."""
        return b"".join(map(self.pieces.__getitem__, ids.tolist())).decode("utf-8", errors="replace")

    def ids_text(self, ids: np.ndarray) -> str:
        return ",".join(map(str, ids.tolist()))


@lru_cache(maxsize=2)
def load(path: str) -> ExactEncoder:
    return ExactEncoder(path)


def sha256(data: bytes) -> str:
    return hashlib.sha256(data).hexdigest()


def ranks_file(path: str) -> dict[bytes, int]:
    """Ranks of a ``.tiktoken`` file."""
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
