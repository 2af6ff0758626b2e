"""Pre-tokens of a lower-casing word BPE vocabulary file, and what its merges need.

The file (tokenizers JSON) is the authority. Texts made only of plain Latin characters are cut
by one Python regular expression; any other text goes through the library's own normaliser and
splitter, so both ways give the library's pre-tokens.
"""

from __future__ import annotations

import json
import re
from functools import lru_cache

LETTERS = "a-zªµºß-öø-ÿœ"
#: Characters on which Python's lower() and these classes agree with the library's.
PLAIN = re.compile("[\t\n\r\x20-\x7e\xa1-\xac\xae-\xb1\xb4-\xb8\xba\xbb\xbf-\xffŒœ–—‘’“”…€]*")
CUT = re.compile(f"'s|'t|'re|'ve|'m|'ll|'d|[{LETTERS}]+|[0-9]|[^\\s{LETTERS}0-9]+")


def vocabulary_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_symbols() -> list[str]:
    """The printable stand-in of each byte: itself where visible in Latin-1, else the next free code point from 256."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    spare = iter(range(256, 512))
    return [chr(b) if b in shown else chr(next(spare)) for b in range(256)]


class WordVocabulary:
    """One per worker process; holds the parsed file and the library's tokenizer."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            self.spec = json.load(f)
        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        self.special = {t["content"]: t["id"] for t in self.spec["added_tokens"] if t["special"]}
        self.special_cut = re.compile("|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) or r"(?!)")
        self.symbols = byte_symbols()
        bare = {**self.spec, "added_tokens": [], "normalizer": None, "pre_tokenizer": None, "post_processor": None}
        #: Applies only the merges, to one pre-token written in byte stand-ins.
        self.merges_only = Tokenizer.from_str(json.dumps(bare))

    def stand_ins(self, pretoken: str) -> str:
        return pretoken if pretoken.isascii() and pretoken.isprintable() and " " not in pretoken else "".join(map(self.symbols.__getitem__, pretoken.encode()))

    def pretokens(self, part: str) -> list[str]:
        """Of text without special strings; rare scripts come from the library, already as stand-ins marked by a leading NUL."""
        if PLAIN.fullmatch(part):
            return CUT.findall(part.lower())
        shaped = self.library.normalizer.normalize_str(part)
        return ["\0" + p for p, _ in self.library.pre_tokenizer.pre_tokenize_str(shaped)]

    def written(self, pretoken: str) -> str:
        return pretoken[1:] if pretoken[0] == "\0" else self.stand_ins(pretoken)

    def parts(self, text: str) -> list[str]:
        """Alternately plain parts and special strings, beginning with a plain part."""
        if "<|" not in text:
            return [text]
        out, at = [], 0
        for m in self.special_cut.finditer(text):
            out += [text[at : m.start()], m.group()]
            at = m.end()
        return [*out, text[at:]]


@lru_cache(maxsize=2)
def word_vocabulary(path: str) -> WordVocabulary:
    return WordVocabulary(path)
