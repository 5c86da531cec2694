"""Token ids of a byte-level BPE whose vocabulary a ``tokenizers`` JSON file holds.

The merges are run by ``tiktoken`` over the ranks of that same file, which gives the ids of
``tokenizers`` (tests hold both equal) at about a quarter of the time; a text that its pattern
engine refuses goes to ``tokenizers`` itself. Strings of the file's added tokens get the ids of those
tokens, as ``tokenizers`` does by default: a text is cut at them, and the parts between are encoded.
"""

from __future__ import annotations

import json
import os
import re
from functools import lru_cache

import numpy as np

#: Pre-tokenisation of the public byte-level vocabularies; a fixed value.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def _byte_of() -> dict[str, int]:
    """The printable stand-ins of bytes in such files: printable Latin-1 stands for itself, the rest follow from 256 on."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    others = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(others)}


@lru_cache(maxsize=2)
def _slow(path: str):
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


@lru_cache(maxsize=2)
def _spec(path: str) -> dict:
    with open(path, encoding="utf-8") as f:
        return json.load(f)


@lru_cache(maxsize=2)
def _added(path: str) -> tuple[dict[str, int], re.Pattern | None, bool]:
    """Ids of the added tokens, what finds them, whether they are found as they stand (else ``tokenizers`` cuts the text)."""
    spec = _spec(path).get("added_tokens", ())
    ids = {x["content"]: x["id"] for x in spec if x["content"]}
    plain = not any(x.get(k) for x in spec for k in ("lstrip", "rstrip", "single_word"))
    return ids, re.compile("(" + "|".join(map(re.escape, sorted(ids, key=len, reverse=True))) + ")") if ids else None, plain


@lru_cache(maxsize=2)
def _fast(path: str):
    import tiktoken

    spec = _spec(path)
    table = _byte_of()
    special = {x["content"] for x in spec.get("added_tokens", ())}
    ranks = {bytes(table[ch] for ch in token): i for token, i in spec["model"]["vocab"].items() if token not in special}
    return tiktoken.Encoding("byte_bpe", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})


def encode(text: str, path: str) -> np.ndarray:
    """Little-endian unsigned 32-bit ids."""
    if not text:
        return np.zeros(0, "<u4")
    added, cut, plain = _added(path)
    try:
        if cut is None or not cut.search(text):
            return np.array(_fast(path).encode_ordinary(text), "<u4")
        if plain:
            ids = [[added[x]] if i % 2 else _fast(path).encode_ordinary(x) for i, x in enumerate(cut.split(text))]
            return np.array([i for part in ids for i in part], "<u4")
    except BaseException as e:  # the pattern engine's own panics are not Exceptions
        if isinstance(e, (KeyboardInterrupt, SystemExit, MemoryError)):
            raise
    return np.array(_slow(path).encode(text, add_special_tokens=False).ids, "<u4")
