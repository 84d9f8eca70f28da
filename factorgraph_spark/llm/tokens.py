"""Fast encoding with the public word-level BPE vocabulary, identical to the tokenizers library.

The vocabulary's pre-tokeniser never lets a token cross white space, so a text's ids are those of its white-space chunks in a row. Chunks
recur; each worker keeps a bounded table of them. A chunk that is not there is encoded by tiktoken with the same merge ranks if it is made of
letters only (ASCII or Latin-1, lower-cased here), and by the tokenizers library itself in every other case.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterable, Iterator

import numpy as np

#: Chunks that a worker remembers; the table is emptied when it is full.
REMEMBERED = 250_000

#: Characters that are split together.
TOGETHER = 300_000

#: Letters, then ASCII punctuation other than the apostrophe.
_PLAIN = re.compile(r"([a-zß-öø-ÿ]+)([!-&(-/:-@\[-`{-~]*)")
_END = "\x00"


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def _byte_letters() -> dict[str, int]:
    """The usual printable stand-ins of byte-level vocabularies: a letter for each byte."""
    keep = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out, spare = {chr(b): b for b in keep}, 256
    for b in range(256):
        if b not in keep:
            out[chr(spare)] = b
            spare += 1
    return out


class WordTokens:
    _tables: dict[str, tuple] = {}

    def __init__(self, vocabulary: str | None = None):
        vocabulary = vocabulary or default_vocabulary()
        if vocabulary not in self._tables:
            self._tables[vocabulary] = self._load(vocabulary)
        self.slow, self.fast, self.is_end = self._tables[vocabulary]
        self.known: dict[str, bytes] = {"": b""}

    @staticmethod
    def _load(vocabulary: str):
        import tiktoken
        from tokenizers import Tokenizer

        slow = Tokenizer.from_file(vocabulary)
        with open(vocabulary, encoding="utf-8") as f:
            model = json.load(f)["model"]
        letters, ranks = _byte_letters(), {}
        for token, k in model["vocab"].items():
            if token.startswith("<|") and token.endswith("|>") and len(token) > 4:
                continue
            stem = token[:-4] if token.endswith("</w>") and len(token) > 4 else token
            ranks[bytes(letters[c] for c in stem) + (b"\x00" if stem is not token else b"")] = k
        ranks.setdefault(b"\x00", max(ranks.values()) + 1)
        is_end = np.zeros(max(ranks.values()) + 1, dtype=bool)
        is_end[[k for token, k in ranks.items() if token.endswith(b"\x00")]] = True
        return slow, tiktoken.Encoding("words", pat_str=r"[^\x00]+\x00", mergeable_ranks=ranks, special_tokens={}), is_end

    def _learn(self, chunks: set[str]) -> None:
        """Adds the ids of chunks: plain ones all in one call, told apart by the tokens that end a word."""
        plain, parts, last, ends = [], [], [], 0
        for c in chunks:
            if m := _PLAIN.fullmatch(c.lower()):
                plain.append(c)
                parts.append(f"{m[1]}{_END}{m[2]}{_END}" if m[2] else m[1] + _END)
                ends += 1 + bool(m[2])
                last.append(ends - 1)
            else:
                self.known[c] = np.array(self.slow.encode(c, add_special_tokens=False).ids, dtype="<u4").tobytes()
        if plain:
            ids = np.array(self.fast.encode_ordinary("".join(parts)), dtype="<u4")
            stops = (4 * (np.flatnonzero(self.is_end[ids])[last] + 1)).tolist()
            packed = ids.tobytes()
            self.known.update(zip(plain, [packed[a:b] for a, b in zip([0, *stops], stops)]))

    def encode_many(self, texts: Iterable[str]) -> Iterator[bytes]:
        """The ids of each text as little-endian unsigned 32-bit numbers in a row."""
        held, size = [], 0
        for text in texts:
            held.append(text.replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" "))
            size += len(text)
            if size > TOGETHER:
                yield from self._encode_held(held)
                held, size = [], 0
        yield from self._encode_held(held)

    def _encode_held(self, held: list[list[str]]) -> Iterator[bytes]:
        if len(self.known) > REMEMBERED:
            self.known = {"": b""}
        self._learn(set().union(*held).difference(self.known))
        get = self.known.__getitem__
        for chunks in held:
            yield b"".join(map(get, chunks))
