"""Byte-level BPE ids, as the tokenizers library gives them, at a few times its speed.

``file`` is the JSON file of the tokenizers library.  Where the same vocabulary lies
beside it as a ``.tiktoken`` file of ranks, ids come from the tiktoken library (tests hold
both against each other); otherwise from tokenizers.  Strings of special tokens in a text
are ordinary text.  Paths are parameters; nothing of them is copied.
"""

from __future__ import annotations

import base64
import os
from functools import lru_cache

import numpy as np


def default_file() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


class Encoder:
    def __init__(self, file: str, fast: bool = True):
        ranks_file = os.path.splitext(file)[0] + ".tiktoken"
        self._tik = None
        if fast and os.path.exists(ranks_file):
            import public_tokenizers
            import tiktoken

            with open(ranks_file, "rb") as lines:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
            self._tik = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
            self.lengths = np.zeros(max(ranks.values()) + 1, np.int64)
            for token, rank in ranks.items():
                self.lengths[rank] = len(token)
        else:
            from tokenizers import Tokenizer

            self._hf = Tokenizer.from_file(file)
            self._hf.encode_special_tokens = True
            size = self._hf.get_vocab_size()
            self.lengths = np.array([len(t) if (t := self._hf.id_to_token(i)) else 0 for i in range(size)], np.int64)  # one character stands for a byte

    def ids(self, text: str) -> np.ndarray:
        if self._tik is not None:
            return self._tik.encode_to_numpy(text, disallowed_special=())
        return np.array(self._hf.encode(text, add_special_tokens=False).ids, np.uint32)


@lru_cache(maxsize=4)
def encoder(file: str, fast: bool = True) -> Encoder:
    """One for each process and file."""
    return Encoder(file, fast)
