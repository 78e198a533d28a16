"""Token ids of whole texts, by the tokenizers library, with a bounded cache of chunks.

Both vocabularies in use split a text into words, runs of signs and white space before
they merge characters, so that the ids of a text are those of its chunks in a row.
`ChunkEncoder` cuts only where such a split is certain, encodes each distinct chunk once
in a while, and hands every other text to the tokenizer as a whole.
"""

from __future__ import annotations

import os
import re
from array import array
from collections.abc import Iterable
from functools import cache
from itertools import pairwise

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Distinct chunks of one generation (about 200 bytes each); a worker remembers two, and forgets the older one beyond that.
MOST_CHUNKS, LONGEST_CHUNK = 700_000, 48
#: A chunk that starts so has no space before it.
BARE = b"\x00"
#: Where a chunk can't be cut off with certainty: white space in a row or the mark itself. Most texts have no white space but these two, and are told by plain searches.
_UNSURE, _RARE = re.compile(r"\s\s|\x00"), re.compile("[\x00\t\r\x0b\x0c\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")
_ROWS_OF_SPACE = ("  ", " \n", "\n ", "\n\n")
#: A stop or comma before white space that doesn't follow a Latin letter.
_ODD_STOP = re.compile("[.,](?<![A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f][.,])(?=[ \\n])")


def _unsure(text: str) -> bool:
    return bool(_UNSURE.search(text)) if _RARE.search(text) else any(x in text for x in _ROWS_OF_SPACE)


def _is_word(chunk: bytes) -> bool:
    """Latin letters only."""
    return chunk.isalpha() or (bool(chunk) and (text := chunk.decode()).isalpha() and max(text) < "\u0250")


class ChunkEncoder:
    """bytes of little-endian unsigned 32-bit ids for each text.

    spaced: a chunk keeps the space before it (byte-level vocabularies); else white space
    is dropped, case too, and chunks stand alone (word-end vocabularies).
    """

    def __init__(self, path: str, spaced: bool) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.model, self.spaced = Tokenizer.from_file(path), spaced
        #: Added tokens, which the library finds in a text before it splits; a text that holds one, in any case, goes to it as a whole.
        self.added = sorted({t.content.lower() for t in self.model.get_added_tokens_decoder().values()})
        self.starts = {re.match("[^A-Za-z]*", x)[0] for x in self.added}
        self.known: dict[bytes, bytes] = {}
        self.older: dict[bytes, bytes] = {}
        vocabulary = self.model.get_vocab()
        #: Ids that start (spaced) or end a word of letters.
        self.edge = np.zeros(max(vocabulary.values()) + 1, bool)
        for token, k in vocabulary.items():
            self.edge[k] = token.startswith("\u0120") if spaced else token.endswith("</w>")

    def _plain(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.model.encode_batch_fast(texts, add_special_tokens=False)]

    def _words(self, words: list[bytes]) -> list[bytes]:
        """Words of letters: many in one call, cut at the ids that start or end a word."""
        out: list[bytes] = []
        for at in range(0, len(words), 2000):
            some = words[at : at + 2000]
            ids = np.array(self.model.encode_batch_fast([(" " * self.spaced + b" ".join(some).decode())], add_special_tokens=False)[0].ids, "<u4")
            edges = np.flatnonzero(self.edge[ids]) + (not self.spaced)
            bounds = [*edges.tolist(), len(ids)] if self.spaced else [0, *edges.tolist()]
            if len(bounds) != len(some) + 1:
                out += self._plain([" " * self.spaced + w.decode() for w in some])
                continue
            raw = ids.tobytes()
            out += [raw[4 * a : 4 * b] for a, b in pairwise(bounds)]
        return out

    def _bare_words(self, words: list[bytes]) -> list[bytes]:
        """Words of letters without a space before them: many in one call, with line feeds between."""
        feed = self.model.encode("\n", add_special_tokens=False).ids
        out: list[bytes] = []
        for at in range(0, len(words), 2000):
            some = [w[1:].decode() for w in words[at : at + 2000]]
            ids = np.array(self.model.encode_batch_fast(["\n".join(some)], add_special_tokens=False)[0].ids, "<u4")
            cuts = np.flatnonzero(ids == feed[0]).tolist()
            if len(feed) != 1 or len(cuts) != len(some) - 1:
                out += self._plain(some)
                continue
            raw = ids.tobytes()
            out += [raw[4 * (a + 1) : 4 * b] for a, b in pairwise([-1, *cuts, len(ids)])]
        return out

    def _marked(self, text: str) -> bytes | None:
        """The text with a space wherever a chunk ends; None if it can't be cut."""
        if any(x in text for x in self.starts) and any(x in text.lower() for x in self.added):
            return None
        raw = text.encode()
        if self.spaced:
            if _unsure(text):
                return None
            if not _ODD_STOP.search(text):
                raw = raw.replace(b", ", b" \x00, ").replace(b". ", b" \x00. ").replace(b".\n", b" \x00.\n")
            return BARE + raw.replace(b"\n", b" \x00\n \x00")
        raw = raw.lower()  # A-Z alone; the tokenizer lowers the rest
        if not _ODD_STOP.search(text):
            raw = raw.replace(b", ", b" , ").replace(b". ", b" . ").replace(b".\n", b" . ")
        return raw.replace(b"\n", b" ")

    def _look_up(self, chunks: list[bytes]) -> list[bytes]:
        """Ids of distinct chunks."""
        if len(self.known) > MOST_CHUNKS:
            self.known, self.older = {}, self.known
        known, older = self.known, self.older
        out = list(map(known.get, chunks))
        words, bare, rest = [], [], []
        for k, c in enumerate(chunks):
            if out[k] is None:
                found = older.get(c)
                if found is not None:
                    out[k] = known[c] = found
                else:
                    (words if _is_word(c) else bare if self.spaced and c[:1] == BARE and _is_word(c[1:]) else rest).append(k)
        shown = [(c if not self.spaced else c[1:] if c[:1] == BARE else b" " + c).decode() for c in (chunks[k] for k in rest)]
        for at, ids in ((words, self._words([chunks[k] for k in words])), (bare, self._bare_words([chunks[k] for k in bare])), (rest, self._plain(shown))):
            for k, x in zip(at, ids, strict=True):
                out[k] = x
                if len(chunks[k]) <= LONGEST_CHUNK:
                    known[chunks[k]] = x
        return out

    def encode(self, texts: Iterable[str | None]) -> list[bytes]:
        """Null counts as empty."""
        held = [t or "" for t in texts]
        marked = [self._marked(t) for t in held]
        whole = iter(self._plain([t for t, m in zip(held, marked, strict=True) if m is None]))
        lists = pc.split_pattern(pa.array([m for m in marked if m is not None], pa.large_binary()), b" ")
        each = lists.values.dictionary_encode()
        ids = pa.array(self._look_up(each.dictionary.to_pylist()), pa.large_binary()).take(each.indices)
        if not len(ids):
            return list(whole)
        starts, raw = np.frombuffer(ids.buffers()[1], np.int64)[lists.offsets.to_numpy()].tolist(), memoryview(ids.buffers()[2] or b"")
        joined = iter([bytes(raw[a:b]) for a, b in pairwise(starts)])
        return [next(whole) if m is None else next(joined) for m in marked]


@cache
def encoder(name: str, spaced: bool) -> ChunkEncoder:
    """One for each Python worker. name: a file's path, or a name that public_tokenizers knows."""
    if not os.path.isabs(name):
        import public_tokenizers

        name = public_tokenizers.path(name)
    return ChunkEncoder(name, spaced)
