"""Token ids by public engines; the fast way into packing and storage."""

from __future__ import annotations

import numpy as np
import regex

from .bpe import vocabulary

#: Pattern that the vocabulary file's byte-level pre-tokenizer has by definition.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: The same cuts where no white space touches other white space: nothing looks ahead, so the engine runs it as an automaton.
LONE = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s"
#: Characters that engines don't agree to call white space, or that one of them calls so in another way.
_ODD_ASCII = "\x0b\x0c\x1c\x1d\x1e\x1f"
_ODD = regex.compile(r"[\x0b\x0c\x1c-\x1f\x85\xa0\u1680\u180e\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")


def _lone(text: str) -> bool:
    """Of a text without odd characters: does surely no white space touch other white space?"""
    return not ("  " in text or "\n\n" in text or " \n" in text or "\n " in text or "\t" in text or "\r" in text)


class Library:
    """The tokenizers library's ids. A rank-based engine over the same file gives them at a third of the cost; texts with odd
    white space or with a special token's name go through the library itself."""

    def __init__(self, path: str):
        import tiktoken
        from tokenizers import Tokenizer

        self.v = vocabulary(path)
        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.engine, self.plain = (tiktoken.Encoding("file", pat_str=p, mergeable_ranks=self.v.by_bytes, special_tokens={}) for p in (SPLIT, LONE))

    def ids(self, text: str) -> list[int]:
        odd = any(c in text for c in _ODD_ASCII) if text.isascii() else _ODD.search(text)
        if odd or any(s in text for s in self.v.special):
            return self.library.encode(text, add_special_tokens=False).ids
        return (self.plain if _lone(text) else self.engine).encode_ordinary(text)

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        return [np.array(self.ids(t), self.v.kind).tobytes() for t in texts]
