"""Exact byte-level BPE encoding with a memo of space-delimited chunks.

The vocabulary's pre-tokenizer never joins a non-space character to the space that follows it, so a text may be cut
before every single space that stands between two non-space characters, the cuts encoded on their own and the ids
joined again.  Most chunks of a corpus repeat, hence a memo from chunk to a place in one array of ids: Arrow splits a run of
texts and numbers its distinct chunks, each is looked up once, and numpy gathers the ids of all.  The ``tokenizers`` library
encodes each unseen chunk.  Texts with doubled, leading or trailing white space are handed to the library whole.
"""

from __future__ import annotations

import os
import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Chunks kept in one worker's memo, and the longest chunk worth keeping: a bound on memory, not on what is encoded.
MEMO_CHUNKS = 700_000
MEMO_CHARS = 40
#: Characters of a run of texts that is encoded at once (or one longer text).
RUN_CHARS = 3_000_000
#: What a chunk must not hold for its pieces to be told apart by kinds of characters alone: contractions, runs of white
#: space, and characters other than ASCII and the Latin letters up to U+024F.
UNSETTLED = re.compile("'|\\s\\s|[^\\x00-\\x7f\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f]|[\\x1c-\\x1f]")


def _kind(c: str) -> str:
    """Kind of a byte (as a Latin-1 character) inside a settled chunk."""
    return "L" if c.isascii() and c.isalpha() or c >= "\x80" else "N" if c.isdigit() else "S" if c.isspace() else "P"


def _reachable(raw: str) -> bool:
    """Whether a settled chunk's UTF-8 can hold these bytes: of the lead bytes, C3 to C9 only."""
    return not re.search("[\xc0-\xc2\xca-\xff]", raw)


def default_vocabulary() -> str:
    """Place of the public byte-level BPE file (looked up where the code runs, so workers resolve their own copy)."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def vocabulary_size(path: str | None = None) -> int:
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path or default_vocabulary()).get_vocab_size(with_added_tokens=True)


class ChunkEncoder:
    """Texts to ids as little-endian unsigned 32-bit bytes.  Strings that name special tokens are ordinary text."""

    def __init__(self, path: str | None = None, memo_chunks: int = MEMO_CHUNKS) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        self._most = memo_chunks
        from tokenizers import Tokenizer, pre_tokenizers

        self._library = Tokenizer.from_file(path or default_vocabulary())
        self._library.encode_special_tokens = True
        visible = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        ascii_text = "".join(map(chr, range(128)))
        # bytes as the characters that stand for them in the vocabulary; lead bytes are printable and stand for themselves
        shown = {c: c for c in map(chr, range(192, 256))}
        shown |= dict(zip(ascii_text, visible.pre_tokenize_str(ascii_text)[0][0], strict=True))
        for c in map(chr, range(128, 0x800)):
            shown.update(zip(c.encode().decode("latin1"), visible.pre_tokenize_str(c)[0][0], strict=True))
        self._shown = str.maketrans(shown)
        by_id = sorted(self._library.get_vocab(with_added_tokens=False).items(), key=lambda x: x[1])
        self._spaced = np.zeros(by_id[-1][1] + 1, dtype=bool)
        plain = dict(zip(shown.values(), shown, strict=True))
        mixed = []
        for token, i in by_id:
            raw = "".join(map(plain.get, token))
            self._spaced[i] = raw[0] == " "
            if len(set(map(_kind, raw[raw[0] == " " :]))) > 1:
                mixed.append(raw)
        # if no token joins two kinds of reachable characters, merges never cross the pieces of a settled chunk
        self._free = not any(m for m in mixed if not UNSETTLED.search(m) and _reachable(m))
        self._clear()

    def _clear(self) -> None:
        """Forget all chunks.  Place 0 is no ids, place 1 is kept for chunks that can't stand alone."""
        self._memo: dict[str, int] = {"": 1}
        self._pool = np.zeros(0, dtype="<u4")
        self._starts, self._sizes = np.zeros(2, dtype=np.int64), np.zeros(2, dtype=np.int64)

    def _whole(self, text: str) -> np.ndarray:
        return np.array(self._library.encode(text, add_special_tokens=False).ids, dtype="<u4")

    def _together(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids and sizes of settled chunks: the merges run over many at once, as none crosses from one piece to the next."""
        ids, sizes = [], []
        for i in range(0, len(chunks), 256):
            own = " " + " ".join(chunks[i : i + 256])
            found = np.array([t.id for t in self._library.model.tokenize(own.encode().decode("latin1").translate(self._shown))], dtype="<u4")
            ids.append(found)
            sizes.append(np.diff(np.append(np.flatnonzero(self._spaced[found]), len(found))))
        return np.concatenate(ids), np.concatenate(sizes)

    def _place(self, ids: list[np.ndarray], sizes: np.ndarray) -> np.ndarray:
        """Put ids of some chunks into the array; their places."""
        first = len(self._starts)
        at = len(self._pool) + np.concatenate([[0], np.cumsum(sizes)[:-1]])
        self._pool = np.concatenate([self._pool, *ids])
        self._starts, self._sizes = np.concatenate([self._starts, at]), np.concatenate([self._sizes, sizes])
        return np.arange(first, first + len(sizes))

    def _learn(self, missing: list[str]) -> np.ndarray:
        """Places of chunks that aren't known, as they follow a space; 1: one that can't stand alone."""
        places = np.ones(len(missing), dtype=np.int64)
        settled = np.full(len(missing), self._free)
        if self._free:
            joined = " ".join(missing)
            ends = np.cumsum(np.fromiter(map(len, missing), dtype=np.int64, count=len(missing)) + 1)
            spans = np.array([m.span() for m in UNSETTLED.finditer(joined)], dtype=np.int64).reshape(-1, 2)
            settled[np.searchsorted(ends, spans[:, 0], side="right")] = False
            settled[np.minimum(np.searchsorted(ends, spans[:, 1] - 1, side="right"), len(missing) - 1)] = False
            settled &= (ends - np.concatenate([[0], ends[:-1]])) > 1
            for edge in (missing[0], missing[-1]):  # white space at the ends of the joined text has no second beside it
                if edge and (edge[0].isspace() or edge[-1].isspace()):
                    settled[[0, -1]] = False
        alone = np.flatnonzero(settled)
        if len(alone):
            ids, sizes = self._together([missing[i] for i in alone.tolist()])
            places[alone] = self._place([ids], sizes)
        rest = [i for i in np.flatnonzero(~settled).tolist() if (x := missing[i]) and not x[0].isspace() and not x[-1].isspace()]
        if rest:
            own = [self._whole(" " + missing[i]) for i in rest]
            places[rest] = self._place(own, np.array([len(x) for x in own]))
        return places

    def encode_run(self, texts: pa.Array, end: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """All ids of some texts in a row, and where each text's begin and end; ``end`` closes each.  Null texts are empty."""
        texts = texts.cast(pa.large_string()).fill_null("")
        n = len(texts)
        if len(self._memo) > self._most:
            self._clear()
        parts = pc.split_pattern(texts, " ")
        firsts = parts.offsets.to_numpy().astype(np.int64) - parts.offsets[0].as_py()
        coded = parts.flatten().dictionary_encode()
        chunks, which = coded.dictionary.to_numpy(zero_copy_only=False).tolist(), coded.indices.to_numpy()
        get = self._memo.get
        places = np.array([get(c, -1) for c in chunks], dtype=np.int32)
        heads = which[firsts[:-1]]
        follow = np.ones(len(which), dtype=bool)
        follow[firsts[:-1]] = False
        used = np.zeros(len(chunks), dtype=bool)
        used[which[follow]] = True
        lacks = np.flatnonzero((places < 0) & used)
        short = np.array([len(chunks[i]) <= MEMO_CHARS for i in lacks.tolist()], dtype=bool)
        kept = lacks[short]
        if len(kept):
            own = [chunks[i] for i in kept.tolist()]
            places[kept] = self._learn(own)
            self._memo.update(zip(own, places[kept].tolist(), strict=True))
        state = len(self._pool), len(self._starts)  # what follows is for this run alone
        if not short.all():
            places[lacks[~short]] = self._learn([chunks[i] for i in lacks[~short].tolist()])
        at = places[which]
        at[~follow] = 0
        bad = np.zeros(n, dtype=bool)
        bad[np.searchsorted(firsts, np.flatnonzero(follow & (at == 1)), side="right") - 1] = True
        opening = [chunks[i] for i in heads.tolist()]
        alone = np.diff(firsts) == 1
        own, of = [], {}
        for i, c in enumerate(opening):
            if bad[i] or (not alone[i] and (not c or c[-1].isspace())):
                bad[i] = True
                own.append(self._whole(texts[i].as_py()))
            elif c:
                if c not in of:
                    of[c] = self._whole(c)
                own.append(of[c])
            else:
                own.append(self._pool[:0])
        if bad.any():
            at[np.repeat(bad, np.diff(firsts))] = 0
        if n:
            at[firsts[:-1]] = self._place(own, np.array([len(x) for x in own], dtype=np.int64))
        bounds = firsts
        if end is not None:
            at = np.insert(at, firsts[1:], self._place([np.array([end], dtype="<u4")], np.array([1])))
            bounds = firsts + np.arange(n + 1)
        sizes = self._sizes[at]
        stops = np.concatenate([[0], np.cumsum(sizes)])
        kind = np.int32 if max(stops[-1], len(self._pool)) < 2**31 else np.int64  # half the memory of the largest arrays here
        index = np.repeat((self._starts[at] - stops[:-1]).astype(kind), sizes)
        index += np.arange(stops[-1], dtype=kind)
        flat = self._pool[index]
        self._pool, self._starts, self._sizes = self._pool[: state[0]], self._starts[: state[1]], self._sizes[: state[1]]
        return flat, stops[bounds]

    def runs(self, texts: pa.Array) -> list[tuple[int, int]]:
        """Ranges of texts to encode at once."""
        ends = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64) + 1)
        out, at = [], 0
        while at < len(ends):
            before = int(ends[at - 1]) if at else 0
            stop = max(at + 1, int(np.searchsorted(ends, before + RUN_CHARS, side="right")))
            out.append((at, stop))
            at = stop
        return out

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit bytes."""
        column, out = pa.array(texts, pa.large_string()), []
        for a, b in self.runs(column):
            flat, at = self.encode_run(column.slice(a, b - a))
            raw, cuts = flat.tobytes(), (at * 4).tolist()
            out += [raw[x:y] for x, y in zip(cuts, cuts[1:])]
        return out


_KEPT: dict[tuple, ChunkEncoder] = {}


def shared_encoder(path: str | None = None, memo_chunks: int = MEMO_CHUNKS) -> ChunkEncoder:
    """The process's encoder: a worker keeps it, with its memo, from task to task."""
    if (path, memo_chunks) not in _KEPT:
        _KEPT.clear()
        _KEPT[path, memo_chunks] = ChunkEncoder(path, memo_chunks)
    return _KEPT[path, memo_chunks]
