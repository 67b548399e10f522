"""Token ids of whole texts, on executors, from vocabulary files given by path."""

from __future__ import annotations

import base64
import re
from collections.abc import Iterator

import numpy as np

#: Split pattern and special token of the byte-level vocabulary, fixed values of its format.
END_OF_TEXT = ("<|endoftext|>", 50256)
#: Runs of white space (Unicode's property) that the split pattern's engine is spared: it keeps one state a character there.
BLANKS = "[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]"
LONG_RUN = 50_000
LONG_BLANK = re.compile(f"(?<!{BLANKS}){BLANKS}{{{LONG_RUN},}}")


def default_vocabulary(name: str = "byte_bpe_50k.tiktoken") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def encoder(path: str):
    """text -> uint32 ids. A .tiktoken file is read as ranks, a .json file by the tokenizers library; both give the same ids."""
    if path.endswith(".json"):
        from tokenizers import Tokenizer

        bpe = Tokenizer.from_file(path)
        return lambda text: np.array(bpe.encode(text, add_special_tokens=False).ids, dtype=np.uint32)
    import public_tokenizers
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    bpe = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=dict([END_OF_TEXT]))

    def ids(text: str) -> np.ndarray:
        if len(text) < LONG_RUN or not LONG_BLANK.search(text):
            return np.array(bpe.encode(text, allowed_special="all"), dtype=np.uint32)
        return np.array([i for part, whole in blank_runs(text) for i in (bpe._encode_single_piece(part) if whole else bpe.encode(part, allowed_special="all"))], dtype=np.uint32)

    return ids


def blank_runs(text: str) -> Iterator[tuple[str, bool]]:
    """The text in parts: (a long run of blanks, True) and (what lies between, False); encoding them apart gives the ids of the whole.

    No token but one of blanks holds two blanks, so none reaches over the front of a run. The pattern takes of a run all but its last
    blank as one token, or the whole run where the text or a special token ends it; what follows is split from there on as before.
    """
    at = 0
    for run in LONG_BLANK.finditer(text):
        end = run.end() if run.end() == len(text) or text.startswith(END_OF_TEXT[0], run.end()) else run.end() - 1
        if run.start() > at:
            yield text[at : run.start()], False
        yield text[run.start() : end], True
        at = end
    if at < len(text):
        yield text[at:], False


def largest_id(path: str) -> int:
    """The largest id of a vocabulary file, special tokens included."""
    if path.endswith(".json"):
        from tokenizers import Tokenizer

        return max(Tokenizer.from_file(path).get_vocab(with_added_tokens=True).values())
    with open(path, "rb") as f:
        return max(END_OF_TEXT[1], *(int(line.split()[1]) for line in f if line.strip()))


def split_points(n: int, cap: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens: all of cap tokens but for the first, which takes the remainder."""
    first = n % cap or cap
    return [(0, first)] + [(s, cap) for s in range(first, n, cap)] if n > cap else [(0, n)]
