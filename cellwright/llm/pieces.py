"""Cached encoding of texts by their space-delimited pieces.

A space followed by a character that is no white space always begins a new pre-token in both public vocabularies, so a
text's ids are those of its pieces, one after another. Each distinct piece of a task is encoded once, in a batch, and
kept in a bounded cache; the ids of a document are then gathered by numpy. Texts that hold an added token's string (or
unusual characters beside a space) go through the library whole.
"""

from __future__ import annotations

import os
import re
from itertools import repeat

import numpy as np

from .common import ragged_index

_ODD = re.compile("[ ](?:[\\s\\x1c-\\x1f\\x85\\u180e\\u200b\\u2060\\ufeff]|\\Z)")
_CUT = re.compile("[ ](?=[^\\s\\x1c-\\x1f\\x85\\u180e\\u200b\\u2060\\ufeff])")


def split_pieces(text: str) -> list[str]:
    """Pieces between those single spaces that begin a pre-token; each but the first stands for a space and itself."""
    return text.split(" ") if _ODD.search(text) is None else _CUT.split(text)


def load(path: str):
    """The library's tokenizer without truncation and padding, kept per worker."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    if path not in _LOADED:
        t = Tokenizer.from_file(path)
        t.no_truncation()
        t.no_padding()
        _LOADED[path] = t
    return _LOADED[path]


#: from here on the installed libraries' character tables differ here and there
PLAIN = "\u0530"
_LOADED: dict[str, object] = {}
_CACHES: dict[tuple, PieceCache] = {}


class PieceCache:
    """piece -> run of ids. Beyond max_entries pieces or max_ids ids the half with the most hits stays, so memory is bounded."""

    def __init__(self, encode_many, max_entries: int = 200_000, max_ids: int = 4_000_000):
        self.encode_many, self.max_entries, self.max_ids = encode_many, max_entries, max_ids
        self.at: dict = {}
        self.flat, self.used = np.zeros(1 << 16, np.int32), 0
        self.start, self.len, self.hits = np.zeros(1 << 14, np.int64), np.zeros(1 << 14, np.int64), np.zeros(1 << 14, np.int64)

    def _shrink(self) -> None:
        n = len(self.at)
        order = np.argsort(-self.hits[:n], kind="stable")[: self.max_entries // 2]
        keep = np.sort(order[np.cumsum(self.len[order]) <= self.max_ids // 2])
        lens, ids = self.ids(keep)
        place = np.full(n, -1)
        place[keep] = np.arange(len(keep))
        self.at = {p: k for p, k in zip(self.at, place.tolist()) if k >= 0}  # entries are numbered in the order of the keys
        self.hits[: len(keep)] = self.hits[keep] // 2
        self.hits[len(keep) :] = 0
        self.flat, self.used = ids.copy(), len(ids)
        self.len[: len(keep)] = lens
        self.start[: len(keep)] = np.cumsum(lens) - lens

    def _add(self, pieces: list) -> None:
        lens, ids = self.encode_many(pieces)
        n, k = len(self.at), len(pieces)
        if self.used + len(ids) > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros(max(len(ids), len(self.flat)), np.int32)])
        while n + k > len(self.start):
            self.start, self.len, self.hits = (np.concatenate([x, np.zeros_like(x)]) for x in (self.start, self.len, self.hits))
        self.flat[self.used : self.used + len(ids)] = ids
        self.len[n : n + k] = lens
        self.start[n : n + k] = self.used + np.cumsum(lens) - lens
        self.used += len(ids)
        self.at.update(zip(pieces, range(n, n + k)))

    def index(self, pieces: list) -> np.ndarray:
        """Entry numbers of the pieces, new ones encoded first. They hold until the next call."""
        if len(self.at) > self.max_entries or self.used > self.max_ids:
            self._shrink()
        got = np.fromiter(map(self.at.get, pieces, repeat(-1)), np.int64, len(pieces))
        if len(gaps := np.flatnonzero(got < 0)):
            missing = [pieces[i] for i in gaps.tolist()]
            self._add(list(dict.fromkeys(missing)))
            got[gaps] = np.fromiter(map(self.at.__getitem__, missing), np.int64, len(gaps))
        self.hits[: len(self.at)] += np.bincount(got, minlength=len(self.at))
        return got

    def ids(self, entries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Number of ids of each entry, and all their ids."""
        lens = self.len[entries]
        return lens, self.flat[ragged_index(self.start[entries], lens)]


def cache(kind: str, path: str, make) -> PieceCache:
    """One cache per worker process, kind and vocabulary; it outlives the task."""
    if (kind, path) not in _CACHES:
        _CACHES[kind, path] = PieceCache(make())
    return _CACHES[kind, path]


def by_library(path: str, ranks: str | None = None):
    """Encodes pieces of a byte-level vocabulary with the tokenizers library, thousands in one call.

    Each piece stands with its space, which begins a pre-token whatever comes before it; its ids end where its bytes end.
    A tuple marks the first piece of a text, which has no space before it: these are encoded one after another by marks.
    ranks: the vocabulary's pre-token pattern. Pieces below PLAIN are then merged by the same ranks in a third of the
    time; ids follow the order of merges in such a vocabulary, so they are the library's. All others go to the library."""
    tok, alone, sizes = load(path), by_marks(path), _token_sizes(path)
    fast = _by_ranks(path, ranks) if ranks else None

    def joined(rest: list, encode) -> tuple[np.ndarray, np.ndarray]:
        lens, ids = [np.zeros(0, np.int64)], [np.zeros(0, np.int32)]
        for a in range(0, len(rest), 4000):
            part = rest[a : a + 4000]
            ids.append(np.asarray(encode("".join(part)), np.int32))
            ends = np.cumsum(np.fromiter((len(p.encode()) for p in part), np.int64, len(part)))
            lens.append(np.diff(np.searchsorted(np.cumsum(sizes[ids[-1]]), ends) + 1, prepend=0))
        return np.concatenate(lens), np.concatenate(ids)

    def encode_many(pieces: list) -> tuple[np.ndarray, np.ndarray]:
        way = np.fromiter((0 if isinstance(p, tuple) else 2 if fast and (p.isascii() or max(p) < PLAIN) else 1 for p in pieces), np.int8, len(pieces))
        lens, found = np.zeros(len(pieces), np.int64), []
        for w in (0, 1, 2):
            at = np.flatnonzero(way == w)
            if len(at):
                own = [pieces[i] for i in at.tolist()]
                n, ids = alone([p[0] for p in own]) if w == 0 else joined([f" {p}" for p in own], (lambda t: tok.encode(t, add_special_tokens=False).ids) if w == 1 else fast)
                lens[at] = n
                found.append((at, n, ids))
        if len(found) == 1:
            return lens, found[0][2]
        out, start = np.empty(int(lens.sum()), np.int32), np.cumsum(lens) - lens
        for at, n, ids in found:
            out[ragged_index(start[at], n)] = ids
        return lens, out

    return encode_many


def byte_ranks(path: str) -> dict[bytes, int]:
    """Bytes of each ordinary token of a byte-level vocabulary file, with its id."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that stand for themselves; the others are shifted above 255
    shown = dict(zip(plain, plain)) | {b: 256 + k for k, b in enumerate(b for b in range(256) if b not in plain)}
    back = {chr(c): b for b, c in shown.items()}
    extra = set(special_strings(path))
    return {bytes(back[c] for c in t): i for t, i in load(path).get_vocab(with_added_tokens=False).items() if t not in extra}


def _by_ranks(path: str, pattern: str):
    import tiktoken

    return tiktoken.Encoding("pieces", pat_str=pattern, mergeable_ranks=byte_ranks(path), special_tokens={}).encode_ordinary


def _token_sizes(path: str) -> np.ndarray:
    """Bytes of each token of a byte-level vocabulary, whose characters stand for one byte each."""
    tok = load(path)
    return np.fromiter((len(tok.id_to_token(i) or "") for i in range(tok.get_vocab_size())), np.int64, tok.get_vocab_size())


def by_marks(path: str):
    """Encodes pieces with the tokenizers library, thousands in one call, a mark between each two of them.

    Where the vocabulary drops white space and has a control character as a token of its own, that character between
    spaces is the mark. Otherwise, and for pieces that hold it, an added token's string is: the library cuts a text at
    such strings before anything else, so each piece is encoded alone; no piece holds one."""
    tok = load(path)
    mark_id, mark = next((i, t.content) for i, t in tok.get_added_tokens_decoder().items())
    plain = _plain_mark(tok)

    def split(texts: list, mark_id: int, mark: str) -> tuple[np.ndarray, np.ndarray]:
        joined = [mark.join(texts[i : i + 2000]) + mark for i in range(0, len(texts), 2000)]
        ids = np.concatenate([np.asarray(tok.encode(t, add_special_tokens=False).ids, np.int32) for t in joined])
        ends = np.flatnonzero(ids == mark_id)
        return np.diff(ends, prepend=-1) - 1, ids[ids != mark_id]

    def encode_many(texts: list) -> tuple[np.ndarray, np.ndarray]:
        if not plain:
            return split(texts, mark_id, mark)
        odd = [i for i, t in enumerate(texts) if plain[1][1] in t]
        if not odd:
            return split(texts, *plain)
        own = np.zeros(len(texts), bool)
        own[odd] = True
        lens = np.zeros(len(texts), np.int64)
        lens[own], ids = split([texts[i] for i in odd], mark_id, mark)
        rest = np.zeros(0, np.int32)
        if len(odd) < len(texts):
            lens[~own], rest = split([t for t, o in zip(texts, own.tolist()) if not o], *plain)
        out, start = np.empty(int(lens.sum()), np.int32), np.cumsum(lens) - lens
        out[ragged_index(start[own], lens[own])] = ids
        out[ragged_index(start[~own], lens[~own])] = rest
        return lens, out

    return encode_many


def _plain_mark(tok) -> tuple[int, str] | None:
    """Id and text of a control character between spaces that stands as one token and leaves its neighbours as they are."""
    alone = tok.encode("a", add_special_tokens=False).ids
    for c in map(chr, range(1, 9)):
        found = tok.encode(f"a {c} a", add_special_tokens=False).ids
        if len(found) == 2 * len(alone) + 1 and found[: len(alone)] == found[len(alone) + 1 :] == alone and tok.encode(" a ", add_special_tokens=False).ids == alone:
            return found[len(alone)], f" {c} "
    return None


def special_strings(path: str) -> list[str]:
    return [t.content for t in load(path).get_added_tokens_decoder().values()]


def doc_pieces(texts: list[str], special: list[str]) -> tuple[list, np.ndarray, list[int]]:
    """All pieces of the texts, the number of each text, and the texts that must go through the library whole."""
    out: list = []
    counts, whole = np.zeros(len(texts), np.int64), []
    for i, t in enumerate(texts):
        if any(s in t for s in special):
            whole.append(i)
            continue
        p = split_pieces(t)
        p[0] = (p[0],)
        counts[i] = len(p)
        out += p
    return out, counts, whole


def encode_texts(texts: list[str], path: str, ranks: str | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Number of ids of each text, and all ids, as the library gives them without special tokens added; ranks: see by_library."""
    held = cache(f"library {ranks}", path, lambda: by_library(path, ranks))
    pieces, counts, whole = doc_pieces(texts, special_strings(path))
    lens, ids = held.ids(held.index(pieces)) if pieces else (np.zeros(0, np.int64), np.zeros(0, np.int32))
    ends = np.concatenate([[0], np.cumsum(lens)])[np.concatenate([[0], np.cumsum(counts)])]
    if not whole:
        return np.diff(ends), ids
    tok, parts, n = load(path), [], np.diff(ends)
    for i in range(len(texts)):
        if not counts[i]:
            own = np.asarray(tok.encode(texts[i], add_special_tokens=False).ids, np.int32)
            n[i] = len(own)
            parts.append(own)
        else:
            parts.append(ids[ends[i] : ends[i + 1]])
    return n, np.concatenate(parts)
