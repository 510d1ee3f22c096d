"""Token ids of whole texts by the tokenizers library, word by word with a cache."""

from __future__ import annotations

import os
import re

import numpy as np

from nearcopy.llm.common import claim

#: Words whose ids one Python worker keeps; others are encoded again when they come.
CACHE_WORDS = 800_000
#: Words of letters that are encoded as one text.
JOINED = 2000
_cached: dict[str, CachedTokenizer] = {}
#: White space after a blank: there a cut could change the split into words.
_unsafe = re.compile(r" \s")
#: A comma or full stop that isn't behind a letter or digit, and a new line beside white space: in such texts these
#: stay with what is around them.
_odd_stop, _odd_line = re.compile(r"[,.](?<=[\W_].)|^[,.]", re.S), re.compile(r"\n\s|\n(?<=\s\n)")


def public_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class CachedTokenizer:
    """Ids as little-endian bytes. A text is cut before each blank between two solid characters; for both kinds
    of pre-tokenizer in use (a word with the blank before it; white space dropped) no token spans such a cut, so
    the parts' ids in a row are the text's. Cuts before commas and full stops behind letters and at single new lines
    are such cuts too. Texts where a
    blank stands before other white space go through whole."""

    def __init__(self, path: str, cache_words: int = CACHE_WORDS):
        self.cache_words = cache_words
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.width = 2 if self.tokenizer.get_vocab_size() <= 1 << 16 else 4
        self.kind = np.dtype(f"<u{self.width}")
        self.known: dict[str, bytes] = {}
        vocab = self.tokenizer.get_vocab()
        self.closed = any(t.endswith("</w>") for t in vocab)  # the last id of a word shows, else the first
        self.edge = np.zeros(max(vocab.values()) + 1, bool)
        self.edge[
            [i for t, i in vocab.items() if (t.endswith("</w>") if self.closed else t.startswith("\u0120"))]
        ] = True

    @staticmethod
    def of(path: str, cache_words: int = CACHE_WORDS) -> CachedTokenizer:
        claim("tokens", _cached.clear)
        if path not in _cached:
            _cached[path] = CachedTokenizer(path, cache_words)
        return _cached[path]

    def _encode(self, texts: list[str]) -> list[bytes]:
        return [np.array(e.ids, self.kind).tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _encode_words(self, words: set[str]) -> dict[str, bytes]:
        """Words of letters behind a blank go together and are told apart by the ids that begin or end a word; where
        their
        number isn't the words', and for all other words, each goes by itself."""
        joined, single, out = [], [], {}
        for w in words:
            if w[0] == " ":
                (joined if w[1:].isalpha() else single).append(w)
            else:
                (joined if self.closed and w.isalpha() else single).append(w)
        groups = [joined[i : i + JOINED] for i in range(0, len(joined), JOINED)]
        for a in range(0, len(groups), 16):
            for group, e in zip(
                groups[a : a + 16],
                self.tokenizer.encode_batch_fast(
                    [(" " * self.closed).join(g) for g in groups[a : a + 16]], add_special_tokens=False
                ),
                strict=True,
            ):
                ids = np.array(e.ids, self.kind)
                edges = np.flatnonzero(self.edge[ids])
                if len(edges) != len(group):
                    single += group
                    continue
                cuts = ((edges + 1 if self.closed else np.append(edges[1:], len(ids))) * self.width).tolist()
                raw, at = ids.tobytes(), 0
                for w, c in zip(group, cuts, strict=True):
                    out[w] = raw[at:c]
                    at = c
        for a in range(0, len(single), 20_000):
            out.update(zip(single[a : a + 20_000], self._encode(single[a : a + 20_000]), strict=True))
        return out

    def encode(self, texts: list[str | None]) -> list[bytes]:
        parts: list[list[str] | None] = []
        missing: set[str] = set()
        whole: list[int] = []
        for i, t in enumerate(texts):
            if not t:
                parts.append([])
            elif _unsafe.search(t):
                parts.append(None)
                whole.append(i)
            else:
                if "\0" in t:
                    cut = [t]
                elif _odd_line.search(t) or _odd_stop.search(t):
                    cut = t.replace(" ", "\0 ").split("\0")
                else:
                    cut = t.replace(
                        " ", "\0 "
                    ).replace(",", "\0,").replace(".", "\0.").replace("\n", "\0\n\0").split("\0")
                parts.append(cut)
                missing.update(cut)
        known = self.known
        known[""] = b""
        fresh = self._encode_words({w for w in missing if w not in known})
        known.update(fresh)
        out = [b"" if p is None else b"".join(map(known.__getitem__, p)) for p in parts]
        if len(known) > self.cache_words:
            for w in fresh:
                del known[w]
        for i, ids in zip(whole, self._encode([texts[i] for i in whole]), strict=True):
            out[i] = ids
        return out

    def ids(self, raw: bytes) -> np.ndarray:
        return np.frombuffer(raw, self.kind)


def text_groups(column, limit: int = 4 << 20):
    """(first row, texts) of runs of rows of an Arrow string column, of about `limit` bytes each, so that few are
    Python strings at a time."""
    import pyarrow.compute as pc

    sizes = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    ends = np.cumsum(sizes)
    i = 0
    while i < len(column):
        j = int(np.searchsorted(ends, (ends[i - 1] if i else 0) + limit)) + 1
        texts = column.slice(i, min(j, len(column)) - i).to_pylist()
        yield i, texts
        i = j
