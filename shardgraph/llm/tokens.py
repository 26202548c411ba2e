"""Token ids of a public vocabulary, remembered word by word."""

from __future__ import annotations

import os
import unicodedata
from array import array
from itertools import islice

#: Words that a worker remembers at most.
REMEMBERED = 400_000
#: ASCII marks; a run of them behind letters is a pre-token of its own. An apostrophe may begin one with letters.
MARKS = "".join(chr(k) for k in range(33, 127) if not chr(k).isalnum() and chr(k) != "'")


def byte_letters() -> dict[int, str]:
    """The letter that stands for each byte in byte-level vocabularies: printable Latin-1 for itself, others from U+0100 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    return {b: chr(b) for b in plain} | {b: chr(256 + k) for k, b in enumerate(x for x in range(256) if x not in plain)}


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordIds(dict):
    """Word to its ids, packed as little-endian unsigned 32-bit numbers.

    The vocabulary drops white space and no token spans it, so a text's ids are its words' ids in
    turn. Words are cut at the plain space and line feed only; the tokenizer sees any other space.
    """

    def __init__(self, path: str):
        super().__init__()
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model, self.letters = self.tokenizer.model, byte_letters()

    def look_up(self, word: str) -> bytes:
        """The ids of a word that isn't remembered; words of letters only are one pre-token, so only merges are left to do."""
        if word.isascii():
            if word.isalpha():
                low = word.lower()
                return (low != word and self.get(low)) or array("I", [t.id for t in self.model.tokenize(low)]).tobytes()
        elif word.isalpha() and max(word) <= "ɏ" and (low := word.lower()).isalpha() and unicodedata.is_normalized("NFC", low):
            return (low != word and self.get(low)) or array("I", [t.id for t in self.model.tokenize(low.encode().decode("latin-1").translate(self.letters))]).tobytes()
        if word[-1:] in (".", ",") and "A" <= word[-2:-1] <= "ɏ" and word[-2].isalpha():  # a letter and a mark never share a token
            return self[word[:-1]] + self[word[-1]]
        if (head := word.rstrip(MARKS)) != word and "A" <= head[-1:] <= "ɏ" and head.isalpha():
            return self[head] + self[word[len(head) :]]
        return array("I", self.tokenizer.encode(word, add_special_tokens=False).ids).tobytes()

    def __missing__(self, word: str) -> bytes:
        self[word] = found = self.look_up(word)
        return found

    def packed(self, text: str) -> bytes:
        if len(self) > REMEMBERED:  # words met first are the frequent ones
            kept = dict(islice(self.items(), REMEMBERED // 3))
            self.clear()
            self.update(kept)
        words = text.replace("\n", " ").split(" ")
        found = list(map(self.get, words))
        if None in found:
            found = [self[w] if x is None else x for w, x in zip(words, found, strict=True)]
        return b"".join(found)


_LOADED: dict[str, WordIds] = {}


def word_ids(path: str) -> WordIds:
    """One for each worker and vocabulary."""
    if path not in _LOADED:
        _LOADED[path] = WordIds(path)
    return _LOADED[path]
