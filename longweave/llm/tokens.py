"""Token ids of whole texts by the tokenizers library, with each distinct word encoded once per worker.

A byte-level BPE never merges over the places where its pattern splits, and a space or line feed between two non-space
characters is such a place.  So a text's ids are those of its space-separated pieces, one after another, unless white space
meets white space; such texts, and those that hold an added token's string, are encoded whole.  Pieces come from a cache of bounded size in each worker.
"""

from __future__ import annotations

import os
import zlib
from array import array
from functools import lru_cache
from itertools import compress, count
from operator import not_

import numpy as np

VOCABULARY, END_ID = "byte_bpe_50k.json", 2
CACHE_PIECES = 1_200_000
#: By tokenizer file: the pieces of this generation and of the one before.
_cache: dict[str, tuple[dict[str, bytes | None], dict[str, bytes | None]]] = {}


@lru_cache(maxsize=2)
def tokenizer(path: str):
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


@lru_cache(maxsize=2)
def _added(path: str) -> tuple[str, ...]:
    """Strings that the tokenizer takes out of a text before its pattern splits it."""
    return tuple(a.content for a in tokenizer(path).get_added_tokens_decoder().values() if a.content)


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(VOCABULARY)


def _whole(path: str, text: str) -> bytes:
    return np.array(tokenizer(path).encode_batch_fast([text], add_special_tokens=False)[0].ids, dtype="<u4").tobytes()


@lru_cache(maxsize=2)
def _letters(path: str):
    """The library's model and byte alphabet, if words of letters are single pieces to it: a quicker way for these."""
    from tokenizers import pre_tokenizers

    t = tokenizer(path)
    if not isinstance(t.pre_tokenizer, pre_tokenizers.ByteLevel) or t.pre_tokenizer.add_prefix_space or not t.pre_tokenizer.use_regex:
        return None
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]  # bytes that stand for themselves; others follow 255
    return t.model, {b: 256 + k for k, b in enumerate(x for x in range(256) if x not in shown)}


TAILS = frozenset(".,;:!?|")


def _learn_words(path: str, pieces: list[str], cache: dict[str, bytes | None]) -> list[str]:
    """Learns pieces of letters, with a line feed before or a sign of TAILS after them or not; returns the others.

    Letters are one unit to the tokenizer's pattern; a sign after them is a unit of its own.
    """
    quick = _letters(path)
    if quick is None:
        return pieces
    model, alphabet = quick
    feed, rest = _whole(path, "\n"), []
    tails = {c: _whole(path, c) for c in TAILS}
    tokenize = model.tokenize

    def ids_of_word(core: str, lead: str) -> bytes:
        shown = core if core.isascii() else core.encode().decode("latin-1").translate(alphabet)
        return array("I", [t.id for t in tokenize(lead + shown)]).tobytes()

    for p in pieces:
        if p.isalpha():
            if p not in cache:
                cache[p] = ids_of_word(p, "\u0120")
            continue
        tail = p[-1:] if p[-1:] in TAILS else ""
        bare = p[:-1] if tail else p
        if bare.isalpha():
            if bare not in cache:
                cache[bare] = ids_of_word(bare, "\u0120")
        elif bare[:1] == "\n" and bare[1:].isalpha():
            if bare not in cache:
                cache[bare] = feed + ids_of_word(bare[1:], "")
        else:
            rest.append(p)
            continue
        if tail:
            cache[p] = cache[bare] + tails[tail]
    return rest


def _learn(path: str, pieces: list[str], cache: dict[str, bytes | None]) -> None:
    """Encode pieces in one call, with line feeds between them: a line feed between non-spaces is one id of its own."""
    pieces = _learn_words(path, pieces, cache)
    if not pieces:
        return
    feed = _whole(path, "\n")
    plain = [p for p in pieces if p and not p[0].isspace() and not p[-1].isspace() and "\n" not in p]
    after = [p for p in pieces if len(p) > 1 and p[0] == "\n" and not p[1].isspace() and not p[-1].isspace() and "\n" not in p[1:]]
    for p in {*pieces} - {*plain} - {*after}:
        cache[p] = None
    if len(feed) != 4:  # another vocabulary: no such separator
        cache.update((p, _whole(path, " " + p)) for p in plain)
        cache.update((p, _whole(path, p)) for p in after)
        return
    mark = int(np.frombuffer(feed, "<u4")[0])
    for group, joined, lead in ((plain, "\n ".join(plain), b""), (after, "\n".join(p[1:] for p in after), feed)):
        if group:
            ids = np.frombuffer(raw := _whole(path, (" " if group is plain else "") + joined), "<u4")
            at = np.flatnonzero(ids == mark)
            if len(at) != len(group) - 1:
                cache.update((p, _whole(path, (" " if group is plain else "") + p)) for p in group)
                continue
            ends = [*(4 * at).tolist(), len(raw)]
            begin = 0
            for p, end in zip(group, ends, strict=True):
                cache[p] = lead + raw[begin:end]
                begin = end + 4


def ids_of(texts: list[str | None], path: str) -> list[bytes]:
    """Little-endian unsigned 32-bit ids of each text (null: empty)."""
    cache, before = _cache.get(path) or ({}, {})
    if len(cache) > CACHE_PIECES // 2:  # what was used since the last change stays
        cache, before = {}, cache
    _cache[path] = cache, before
    # a text's first piece has no space before it: it is looked up as if after a line feed, whose id then goes
    feed = len(_whole(path, "\n"))
    added = _added(path)
    split = [None if any(a in (t or "") for a in added) else ("\n" + (t or "")).replace("\n", " \n")[1:].split(" ") for t in texts]
    get, rows, new = cache.get, [], set()
    for pieces in split:
        if pieces is None:
            rows.append((None, ()))
            continue
        row = list(map(get, pieces))
        miss = list(compress(count(), map(not_, row)))  # pieces that aren't known, or can't stand alone
        rows.append((row, miss))
        new.update([pieces[i] for i in miss])
    new = [p for p in new if p not in cache]
    if new:
        old = [p for p in new if p in before]
        cache.update((p, before[p]) for p in old)
        _learn(path, new if not old else [p for p in new if p not in before], cache)
    out = []
    for text, pieces, (row, miss) in zip(texts, split, rows, strict=True):
        if not text:
            out.append(b"")
            continue
        for i in miss:
            row[i] = get(pieces[i])
        try:
            out.append(_whole(path, text) if row is None else b"".join(row)[feed:])
        except TypeError:
            out.append(_whole(path, text))
    return out


def crc(ids: bytes) -> int:
    return zlib.crc32(ids) & 0xFFFFFFFF
