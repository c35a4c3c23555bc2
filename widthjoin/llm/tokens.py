"""Byte-level BPE token ids by public vocabulary files. Vocabularies are read, never trained."""

from __future__ import annotations

import base64
import json

#: Fixed value: how byte-level BPE splits a text before merging (public pattern of these vocabularies).
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: A text is encoded in stretches of about so many characters, cut between a letter and a following single space, where no token can reach across.
STRETCH = 100_000


def vocabulary(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def byte_letters() -> dict[str, int]:
    """The letter that byte-level vocabularies write for each byte: printable Latin-1 ones stand for themselves, the others follow from 256 on."""
    own = [*range(ord("!"), ord("~") + 1), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in own]
    return {chr(b): b for b in own} | {chr(256 + k): b for k, b in enumerate(rest)}


def ranks_of(path: str) -> tuple[dict[bytes, int], dict[str, int]]:
    """Merge ranks and special tokens. A .json vocabulary must number merged tokens in the order of its merges, a .tiktoken file has no special tokens."""
    if not path.endswith(".json"):
        with open(path, "rb") as f:
            return {base64.b64decode(a): int(b) for a, b in (x.split() for x in f if x.strip())}, {}
    with open(path, encoding="utf-8") as f:
        own = json.load(f)
    special = {t["content"]: t["id"] for t in own["added_tokens"]}
    letters, vocab = byte_letters(), own["model"]["vocab"]
    merged = [vocab["".join(m.split(" ") if isinstance(m, str) else m)] for m in own["model"]["merges"]]
    if own["model"]["type"] != "BPE" or own["pre_tokenizer"]["type"] != "ByteLevel" or own["normalizer"] or merged != sorted(merged):
        raise ValueError(f"{path}: not a byte-level BPE with ids in the order of merges")
    return {bytes(letters[c] for c in t): i for t, i in vocab.items() if t not in special}, special


def encoder(path: str):
    """tiktoken's encoder with the merges and special tokens of a vocabulary file: the ids of the tokenizers library at several times its speed.

    Kept with the tiktoken module, which lives as long as the worker; this module's functions come anew with each task.
    """
    import tiktoken

    kept = tiktoken.__dict__.setdefault("_encoders_by_path", {})
    if path not in kept:
        ranks, special = ranks_of(path)
        kept[path] = tiktoken.Encoding("public", pat_str=SPLIT, mergeable_ranks=ranks, special_tokens=special)
    return kept[path]


def stretches(text: str, size: int = STRETCH):
    """The text in parts that are encoded alike alone and together: each cut lies before a space that stands between two letters."""
    at = 0
    while len(text) - at > size:
        cut = at + size
        while cut < len(text) and not (text[cut] == " " and text[cut - 1].isalpha() and text[cut + 1 : cut + 2].isalpha()):
            cut += 1
        yield text[at:cut]
        at = cut
    yield text[at:]


def encode(path: str, text: str) -> list[int]:
    """Ids of a text. Where a special token's name stands in it, that is this token, as the tokenizers library has it."""
    own = encoder(path)
    one = (lambda t: own.encode(t, allowed_special="all")) if own.special_tokens_set else own.encode_ordinary
    if len(text) <= STRETCH:
        return one(text)
    return [i for part in stretches(text) for i in one(part)]
