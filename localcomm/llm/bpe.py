"""Byte-level BPE ids by the tokenizers library, with a bounded cache of words.

Ids are those of `Tokenizer.encode(text, add_special_tokens=False)`. The pre-tokenizer of the byte-level files always
cuts before a blank that follows and precedes a non-space, and around a lone line end, so a text without two
neighbouring spaces and without outer ones is the concatenation of its blank-led words; those are encoded once
each by the library and looked up afterwards. Any other text goes to the library whole.
"""

from __future__ import annotations

import os

import numpy as np

DEFAULT = "byte_bpe_50k.json"
#: Entries of each of the two generations of a worker's word cache.
GENERATION = 400_000
#: White space other than the blank and the line end; a text with any goes to the library whole.
_OTHER_SPACE = [chr(c) for c in (9, 11, 12, 13, 28, 29, 30, 31, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)]
#: Marks that the pre-tokenizer keeps together and apart from letters (not the apostrophe, which may begin a piece such as 's).
_MARKS = "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~"
#: Letters before this one are letters in every version of Unicode.
_PLAIN_LETTERS = "\u0250"
_open: dict[tuple[str, int], "WordCache"] = {}


def tokenizer_path(name: str = DEFAULT) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class WordCache:
    """Ids of blank-led words (`young`, `old`) and of words at a line's start (`first`)."""

    def __init__(self, path: str, words: int = GENERATION):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.words = words
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.first: dict[str, bytes] = {}
        self.tails: dict[str, bytes] = {}
        # In byte-level vocabularies this letter stands for the blank, so it begins the first id of a blank-led word.
        self.leads = np.array([(self.tok.id_to_token(i) or "").startswith("\u0120") for i in range(self.tok.get_vocab_size())])
        self.line_end = self._plain(["\n"])[0]

    def _plain(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.tok.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, words: set[str]) -> None:
        """Words are encoded as one line of blank-led words, cut again where an id begins with the blank."""
        if len(self.young) > self.words:
            self.young, self.old = {}, self.young
        young, old = self.young, self.old
        missing = words.difference(young)
        again = [w for w in missing if w in old]
        young.update((w, old[w]) for w in again)
        missing.difference_update(again)
        # The pre-tokenizer cuts between letters and marks, so a word with marks behind it is its letters' ids and the marks'.
        marked = []
        for w in missing:
            stem = w.rstrip(_MARKS)
            if len(stem) < len(w) and stem.isalpha() and (stem.isascii() or max(stem) < _PLAIN_LETTERS):
                marked.append((w, stem, w[len(stem) :]))
        missing.difference_update([w for w, _, _ in marked])
        for _, stem, _ in marked:
            if stem in old:
                young.setdefault(stem, old[stem])
            elif stem not in young:
                missing.add(stem)
        if len(self.tails) > self.words // 4:
            self.tails = {}
        fresh = list({t for _, _, t in marked}.difference(self.tails))
        self.tails.update(zip(fresh, self._plain(fresh), strict=True))
        new = list(missing)
        for lo in range(0, len(new), 2000):
            part = new[lo : lo + 2000]
            ids = np.array(self.tok.encode_batch_fast([" " + " ".join(part)], add_special_tokens=False)[0].ids, "<u4")
            raw, at = ids.tobytes(), (np.append(np.flatnonzero(self.leads[ids]), len(ids)) * 4).tolist()
            if len(at) != len(part) + 1:
                young.update(zip(part, self._plain([" " + w for w in part]), strict=True))
            else:
                young.update((w, raw[i:j]) for w, i, j in zip(part, at, at[1:], strict=False))
        young.update((w, young[stem] + self.tails[t]) for w, stem, t in marked)

    def encode(self, texts: list[str]) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit integers."""
        out: list[bytes] = []
        for lo in range(0, len(texts), 256):
            some = texts[lo : lo + 256]
            split = [self._split(t) for t in some]
            words, heads = set(), set()
            for lines in split:
                for ws in lines or ():
                    heads.add(ws[0])
                    words.update(ws[1:])
            self._learn(words)
            if len(self.first) > self.words // 4:
                self.first = {}
            fresh = [w for w in heads if w not in self.first]
            self.first.update(zip(fresh, self._plain(fresh), strict=True))
            ids, first = self.young.__getitem__, self.first
            whole = iter(self._plain([t for t, s in zip(some, split, strict=True) if s is None]))
            for lines in split:
                if lines is None:
                    out.append(next(whole))
                else:
                    out.append(self.line_end.join([first[ws[0]] + b"".join(map(ids, ws[1:])) for ws in lines]))
        return out

    @staticmethod
    def _split(text: str) -> list[list[str]] | None:
        """Words by line, or None for a text whose white space isn't single blanks and line ends between words."""
        if not text or "  " in text or "\n\n" in text or " \n" in text or "\n " in text or text[0] in " \n" or text[-1] in " \n" or "<|" in text:
            return None
        for c in _OTHER_SPACE:
            if c in text:
                return None
        return [line.split(" ") for line in text.split("\n")]


def closed(path: str, words: int = GENERATION) -> None:
    """Forget a tokenizer and its words, for workers that go on to other stages."""
    _open.pop((path, words), None)


def opened(path: str, words: int = GENERATION) -> WordCache:
    if (path, words) not in _open:
        _open[path, words] = WordCache(path, words)
    return _open[path, words]
