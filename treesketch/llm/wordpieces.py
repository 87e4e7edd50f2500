"""Encoding with a word-level BPE of the ``tokenizers`` library, at corpus speed.

The tokenizer splits at white space, so the ids of a text are those of its
space-separated chunks in a row. Chunks repeat; their ids are kept. Letters
with a tail of punctuation, the usual chunk, are two pre-tokens, kept apart.
"""

from __future__ import annotations

import re
from collections.abc import Iterable

import numpy as np

# White space of the tokenizer's patterns in Latin-1 (fixed values); Python's isspace also takes the separators 1C to 1F, which are signs there.
WHITE_SPACE = frozenset("\t\n\x0b\x0c\r \x85\xa0")
#: Distinct chunks whose ids a worker keeps (some 80 MB); further ones are encoded again.
KEPT_CHUNKS = 400_000


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordPieceEncoder:
    """Ids of whole texts as little-endian 16-bit (or 32-bit) unsigned bytes.

    Equal to ``Tokenizer.encode(text, add_special_tokens=False).ids``. A null
    text is empty. Texts that hold a special token's string take the library's
    own way.
    """

    def __init__(self, path: str, keep: int = KEPT_CHUNKS):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        size = self.tokenizer.get_vocab_size()
        self.dtype = np.dtype("<u2" if size <= 1 << 16 else "<u4")
        self._ends = np.array([(self.tokenizer.id_to_token(i) or "").endswith("</w>") for i in range(size)])
        self._specials = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self._word_and_tail = re.compile(r"([^\W\d_]+)([!-&(-/:-@\[-`{-~]+)").fullmatch
        self._unusual = re.compile("[^\x00-\u012f\u0131-\u024f]").search
        self._kinds = bytes(39 if c == "'" else 120 if c.isalnum() or c in WHITE_SPACE else 112 for c in map(chr, range(256)))
        self._keep = keep
        self._chunks: dict[str, bytes] = {}
        self._parts: dict[str, bytes] = {}

    def encode(self, texts: Iterable[str | None]) -> list[bytes]:
        whole, split, plain = [], [], True
        for text in texts:
            text = text or ""
            special = "<" in text and any(s in text for s in self._specials)
            whole.append(text if special else None)
            chunks, latin = ([], True) if special else self._cut(text)
            split.append(chunks)
            plain = plain and latin
        fresh = set().union(*split).difference(self._chunks)
        self._encode_chunks(fresh, plain)
        ids = self._chunks.__getitem__
        out = [b"".join(map(ids, chunks)) if text is None else self._library(text) for text, chunks in zip(whole, split)]
        if len(self._chunks) > self._keep:
            for chunk in fresh:
                del self._chunks[chunk]
        return out

    def _cut(self, text: str) -> tuple[list[str], bool]:
        """Chunks whose ids can stand in a row for the text's, and whether all letters are of Latin-1.

        The normaliser lower-cases letter by letter, which is plain in Latin-1,
        so such a text is lower-cased first. A full stop or comma between other
        kinds of characters is a pre-token and becomes its own chunk.
        """
        try:
            kinds = text.encode("latin-1").translate(self._kinds)
        except UnicodeEncodeError:
            return text.replace("\n", " ").split(" "), False
        text = text.lower()
        if b"pp" not in kinds and b"'" not in kinds:
            text = text.replace(".", " . ").replace(",", " , ")
        return text.replace("\n", " ").split(" "), True

    def _library(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, self.dtype).tobytes()

    def _encode_chunks(self, chunks: set[str], plain: bool) -> None:
        known, parts = self._chunks, self._parts
        odd = [] if plain else list(filter(self._unusual, chunks))
        usual = chunks.difference(odd)  # in odd ones marks may leave a letter and join what follows
        words = list(filter(str.isalpha, usual))
        known.update(self._encode_parts(words))
        split = []
        for chunk in usual.difference(words):
            if cut := self._word_and_tail(chunk):
                split.append((chunk, *cut.groups()))
            else:
                odd.append(chunk)
        need = {part for _, word, tail in split for part in (word, tail)}.difference(parts)
        if need:
            parts.update(self._encode_parts(list(need)))
        for chunk, word, tail in split:
            known[chunk] = parts[word] + parts[tail]
        for chunk, e in zip(odd, self.tokenizer.encode_batch_fast(odd, add_special_tokens=False)):
            known[chunk] = np.array(e.ids, self.dtype).tobytes()
        if len(parts) > self._keep // 4:
            for part in need:
                del parts[part]

    def _encode_parts(self, parts: list[str]) -> dict[str, bytes]:
        """One call for all: word-end marks show where each part's ids stop."""
        if not parts:
            return {}
        joined = self.tokenizer.encode_batch_fast([" ".join(parts)], add_special_tokens=False)[0]
        ids = np.array(joined.ids, self.dtype)
        cuts = np.flatnonzero(self._ends[ids]) + 1
        if len(cuts) != len(parts):  # a part holds several pre-tokens after normalisation
            return {p: self._library(p) for p in parts}
        raw, at = ids.tobytes(), [0, *(cuts * self.dtype.itemsize).tolist()]
        return {p: raw[at[i] : at[i + 1]] for i, p in enumerate(parts)}


def text_groups(texts: list[str | None], limit: int = 1 << 20) -> Iterable[tuple[int, int]]:
    """Ranges of consecutive texts of about ``limit`` characters."""
    start = held = 0
    for i, text in enumerate(texts):
        held += len(text or "")
        if held >= limit:
            yield start, i + 1
            start, held = i + 1, 0
    if start < len(texts):
        yield start, len(texts)
