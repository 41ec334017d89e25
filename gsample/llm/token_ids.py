"""Ids of a byte-level tokenizer file, as its own library gives them.

The library is the measure.  Where its rank file is at hand and a text has only characters
of the ranges below, for which both libraries split alike, the rank encoder is used, which
gives the same ids several times faster; other texts go to the library itself.
"""

from __future__ import annotations

import base64
import os
import re
from functools import lru_cache

#: Characters outside these ranges go to the library itself: other alphabets.
UNUSUAL = re.compile("[^\x00-\x7f¡-ɏ‐-‧‰-⁞]")


class IdEncoder:
    def __init__(self, tokenizer_path: str, ranks_path: str | None = None, pattern: str | None = None):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer, self.ranks = Tokenizer.from_file(tokenizer_path), None
        added = self.tokenizer.get_added_tokens_decoder()
        if ranks_path and not any(t.lstrip or t.rstrip or t.single_word or t.normalized for t in added.values()):
            import tiktoken

            with open(ranks_path, "rb") as f:
                ranks = {base64.b64decode(t): int(r) for t, r in map(bytes.split, f)}
            self.ranks = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.special = {t.content: i for i, t in added.items()}

    def ids(self, text: str):
        """Ids as a numpy array of unsigned 32-bit integers."""
        import numpy as np

        if not text:
            return np.zeros(0, "<u4")
        if self.ranks is None or UNUSUAL.search(text) or any(s in text for s in self.special):
            return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4")
        return self.ranks.encode_to_numpy(text, disallowed_special=()).astype("<u4", copy=False)


@lru_cache(maxsize=2)
def load_ids(tokenizer_path: str, ranks_path: str | None, pattern: str | None) -> IdEncoder:
    return IdEncoder(tokenizer_path, ranks_path, pattern)
