"""Encoded texts in Arrow batches.

The vocabulary is a `tokenizers` file. Byte-level BPE files whose merges are ranked by id are run
by tiktoken, which gives the same ids several times as fast; any other file by `tokenizers`.
"""

from __future__ import annotations

import json
from collections.abc import Callable
from functools import lru_cache

import public_tokenizers

VOCABULARY = "byte_bpe_50k.json"


def path(name: str = VOCABULARY) -> str:
    return public_tokenizers.path(name)


def _byte_letters() -> dict[str, int]:
    """The byte-level alphabet: printable bytes stand for themselves, the others follow from 256 on."""
    plain = [*range(ord("!"), ord("~") + 1), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


@lru_cache(maxsize=2)
def encoder(file: str) -> Callable[[list[str]], list[list[int]]]:
    """texts -> ids, without special tokens; their strings in a text are ordinary text."""
    with open(file, encoding="utf-8") as f:
        told = json.load(f)
    vocab, merges, before = told["model"]["vocab"], told["model"].get("merges") or [], told.get("pre_tokenizer") or {}
    letters, special = _byte_letters(), {t["content"] for t in told.get("added_tokens", [])}
    pairs = [m.split(" ") if isinstance(m, str) else m for m in merges]
    ranked = all(vocab.get(a + b) == 256 + i for i, (a, b) in enumerate(pairs)) and len(vocab) - len(special & vocab.keys()) == 256 + len(pairs)
    if ranked and not told.get("normalizer") and before.get("type") == "ByteLevel" and not before.get("add_prefix_space"):
        import tiktoken

        ranks = {bytes(letters[c] for c in token): i for token, i in vocab.items() if token not in special}
        bpe = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        return lambda texts: [bpe.encode_ordinary(t) for t in texts]
    from tokenizers import Tokenizer

    tool = Tokenizer.from_file(file)
    tool.encode_special_tokens = True
    return lambda texts: [e.ids for e in tool.encode_batch(texts, add_special_tokens=False)]
