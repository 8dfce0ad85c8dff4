"""Fast exact encoding with public tokenizer files.

Both byte-pair encodings used here cut a text into pieces before they merge
anything, so a text's ids are its pieces' ids in a row. ``PieceEncoder`` cuts
many texts at once with array operations on their bytes, finds equal pieces by
64-bit hashes and a check of their length and bytes, and sends each piece that it
doesn't know, by its very characters, through the tokenizers library, many in one
call. What it knows are sorted arrays of some 25 bytes for a piece. Texts with
apostrophes or runs of white space are cut by pattern, and any with characters
outside common Latin or a string that the file adds to its vocabulary, such as
an end-of-text mark, go through the library whole.
"""

from __future__ import annotations

import os
import re
from collections.abc import Iterable

import numpy as np

#: Pieces kept by one Python worker, then it starts anew; and those of texts cut by pattern. Bytes cut at once.
KEEP, FEW, CHUNK = 2_000_000, 50_000, 2 << 20
#: The letters and marks of texts that are cut here, and the piece rules of the two encodings.
LETTER = "A-Za-zÀ-ÖØ-öø-įı-ſ"
COMMON = re.compile(rf"[\n -~{LETTER}¡¿«»–—‘’“”…€]*")
ENDINGS = "'s|'t|'re|'ve|'m|'ll|'d"
BYTE_PIECES = re.compile(rf"{ENDINGS}| ?[{LETTER}]+| ?[0-9]+| ?[^\s0-9{LETTER}]+|\s+(?!\S)|\s+")
WORD_PIECES = re.compile(rf"{ENDINGS}|[{LETTER}]+|[0-9]|[^\s0-9{LETTER}]+")

LINE, SPACE, DIGIT, ALPHA, OTHER, STRANGE = range(6)
KIND = np.full(256, STRANGE, np.uint8)
KIND[33:127] = OTHER
KIND[[*range(65, 91), *range(97, 123), *range(0x80, 0xC0), 0xC3, 0xC4, 0xC5]] = ALPHA
KIND[48:58], KIND[32], KIND[10] = DIGIT, SPACE, LINE
KIND[39] = STRANGE  # the apostrophe starts pieces of its own kind
#: The hash of a piece is a polynomial in random values of its bytes, modulo 2**64.
VALUES = np.random.default_rng(7).integers(0, 1 << 64, 256, np.uint64)
BASE = 0x9E3779B97F4A7C15
POWERS = np.cumprod(np.full(CHUNK, BASE, np.uint64), dtype=np.uint64)
BACK = np.cumprod(np.full(CHUNK, pow(BASE, -1, 1 << 64), np.uint64), dtype=np.uint64)
EMPTY = np.zeros(0, np.uint32)


class Known:
    """The ids of pieces by hash: sorted hashes with their checks and places in one array of ids."""

    def __init__(self, kind: type):
        self.kind = kind
        self.clear()

    def clear(self) -> None:
        self.hashes, self.checks = np.zeros(0, np.uint64), np.zeros(0, np.uint32)
        self.starts, self.counts = np.zeros(0, np.uint32), np.zeros(0, np.uint32)
        self.ids, self.used = np.zeros(1 << 16, self.kind), 0

    def find(self, hashes: np.ndarray, checks: np.ndarray) -> np.ndarray:
        """The place of each, or -1."""
        if not len(self.hashes):
            return np.full(len(hashes), -1)
        at = np.minimum(np.searchsorted(self.hashes, hashes), len(self.hashes) - 1)
        return np.where((self.hashes[at] == hashes) & (self.checks[at] == checks), at, -1)

    def add(self, hashes: np.ndarray, checks: np.ndarray, ids: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Keeps ids of new pieces, whose hashes ascend; where each starts."""
        if self.used + len(ids) > len(self.ids):
            self.ids = np.concatenate([self.ids[: self.used], np.zeros(max(len(self.ids), len(ids)), self.kind)])
        self.ids[self.used : self.used + len(ids)] = ids
        starts = (self.used + np.cumsum(counts) - counts).astype(np.uint32)
        self.used += len(ids)
        at = np.searchsorted(self.hashes, hashes)
        for name, values in (("hashes", hashes), ("checks", checks), ("starts", starts), ("counts", counts.astype(np.uint32))):
            setattr(self, name, np.insert(getattr(self, name), at, values))
        return starts


class PieceEncoder:
    """Ids of texts as arrays of unsigned 32-bit integers."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        # the library finds these before it cuts anything, so a text that may hold one goes through it whole
        added = self.library.get_added_tokens_decoder().values()
        self.added = [t.content.encode() for t in added if not t.normalized]
        self.added_lower = [t.content.lower() for t in added if t.normalized]
        vocabulary = self.library.get_vocab()
        ends = [i for token, i in vocabulary.items() if token.endswith("</w>")]
        self.by_word = bool(ends)  # pieces end in tokens of their own kind, white space and case go
        self.pieces = WORD_PIECES if self.by_word else BYTE_PIECES
        self.largest = max(vocabulary.values())
        self.is_end = np.zeros(self.largest + 1, bool)
        self.is_end[ends or self.library.encode("\n", add_special_tokens=False).ids] = True
        self.known = Known(np.uint16 if len(self.is_end) <= 1 << 16 else np.uint32)
        self.few: dict[bytes, np.ndarray] = {}

    def _whole(self, text: str) -> np.ndarray:
        return np.array(self.library.encode(text, add_special_tokens=False).ids, np.uint32)

    def _learn(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of distinct pieces in a row, and how many each has.

        Pieces are joined by what can't merge with them: a space, after which word
        pieces are told apart by their end tokens, or a line end, one id of its own.
        """
        out, counts = [], []
        for first in range(0, len(pieces), 1000):
            some = pieces[first : first + 1000]
            if not any(p.isspace() for p in some):
                joined = (b" " if self.by_word else b"\n").join(some).decode()
                ids = np.array(self.library.encode_batch_fast([joined], add_special_tokens=False)[0].ids, np.uint32)
                ends = self.is_end[ids]
                at = np.flatnonzero(ends)
                lengths = np.diff(np.r_[-1, at]) if self.by_word else np.diff(np.r_[-1, at, len(ids)]) - 1
                if len(lengths) == len(some):
                    out.append(ids if self.by_word else ids[~ends])
                    counts.append(lengths)
                    continue
            single = [self._whole(p.decode()) for p in some]
            out += single
            counts.append(np.array([len(x) for x in single]))
        return np.concatenate(out) if out else EMPTY, np.concatenate(counts) if counts else np.zeros(0, np.int64)

    def _cut(self, raw: bytes, ends: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        """Which of the texts, joined in raw and ending at ends, were cut by their bytes; and their ids.

        White space must stand alone between other characters. A byte piece is a
        run of one kind with the space before it, a line end is its own; a word
        piece is such a run without white space, and each digit.
        """
        b = np.frombuffer(raw, np.uint8)
        kind = KIND[b]
        first = np.zeros(len(b), bool)
        starts = np.r_[0, ends[:-1]]
        first[starts] = True
        white = kind <= SPACE
        before = np.r_[np.uint8(STRANGE), kind[:-1]]
        lone = np.zeros(len(b), bool)  # white space that is followed by white space or the end
        lone[:-1] = white[:-1] & (white[1:] | first[1:])
        lone[-1] = white[-1]
        bad = (kind == STRANGE) | lone
        lead = np.flatnonzero(b >= 0xC3)
        after = b[np.minimum(lead + 1, len(b) - 1)]
        if self.by_word:
            strange = (b[lead] > 0xC3) | (after == 0x97) | (after == 0xB7)
            upper = lead[(b[lead] == 0xC3) & (after >= 0x80) & (after <= 0x9E)] + 1
            b = np.where((b >= 65) & (b <= 90), b + 32, b).astype(np.uint8)
            b[upper] += 32
            raw = b.tobytes()
        else:
            strange = ((b[lead] == 0xC3) & ((after == 0x97) | (after == 0xB7))) | ((b[lead] == 0xC4) & (after == 0xB0))
        bad[lead[strange]] = True
        fine = np.add.reduceat(bad, starts, dtype=np.int64) == 0
        begin = first | (kind != before) | (white if not self.by_word else white | (kind == DIGIT))
        if not self.by_word:  # a space belongs to what follows
            spaced = np.flatnonzero(begin & (before == SPACE) & ~first)
            begin[spaced] = False
        at = np.flatnonzero(begin)
        stop = np.r_[at[1:], len(b)]
        if self.by_word:
            keep = ~white[at]
            at, stop = at[keep], stop[keep]
        total = np.r_[np.uint64(0), np.cumsum(VALUES[b] * POWERS[: len(b)], dtype=np.uint64)]
        hashes = (total[stop] - total[at]) * BACK[at] + (stop - at).astype(np.uint64)
        order = np.argsort(hashes)
        new = np.r_[True, np.diff(hashes[order]) != 0] if len(order) else np.zeros(0, bool)
        sample = order[new]  # a place of each distinct piece
        which = np.empty(len(order), np.int64)
        which[order] = np.cumsum(new) - 1
        # pieces of texts that can't be cut here are never looked up
        text_of = np.searchsorted(ends, at, side="right")
        useful = np.zeros(len(sample), bool)
        useful[which[fine[text_of]]] = True
        sample, place = sample[useful], np.cumsum(useful) - 1
        begins, size = at[sample], stop[sample] - at[sample]
        one = hashes[sample]
        check = (size & 0xFF | b[begins].astype(np.int64) << 8 | b[begins + size - 1].astype(np.int64) << 16 | b[begins + size // 2].astype(np.int64) << 24).astype(np.uint32)
        known = self.known
        if len(known.hashes) > KEEP:
            known.clear()
        met = known.find(one, check)
        new = met < 0
        offset, counts = np.zeros(len(one), np.int64), np.zeros(len(one), np.int64)
        offset[~new], counts[~new] = known.starts[met[~new]], known.counts[met[~new]]
        if new.any():
            ids, counts[new] = self._learn([raw[a:z] for a, z in zip(begins[new].tolist(), (begins + size)[new].tolist(), strict=True)])
            offset[new] = known.add(one[new], check[new], ids, counts[new])
        own = place[which]
        lengths = np.where(useful[which], counts[own], 0) if len(one) else np.zeros(len(which), np.int64)
        done = np.cumsum(lengths)
        total = int(done[-1]) if len(done) else 0
        flat = known.ids[np.repeat(offset[own] - (done - lengths), lengths) + np.arange(total)].astype(np.uint32) if total else EMPTY
        last = np.searchsorted(at, ends)  # pieces before each text's end
        edges = np.r_[0, done][np.r_[0, last]]
        return fine, [flat[a:z] for a, z in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)]

    def _by_pattern(self, text: str) -> np.ndarray:
        pieces = [p.encode() for p in self.pieces.findall(text.lower() if self.by_word else text)]
        if len(self.few) > FEW:
            self.few.clear()
        new = [p for p in dict.fromkeys(pieces) if p not in self.few]
        ids, counts = self._learn(new)
        stops = np.cumsum(counts)
        self.few.update((p, ids[z - n : z].copy()) for p, n, z in zip(new, counts.tolist(), stops.tolist(), strict=True))
        return np.concatenate([self.few[p] for p in pieces]) if pieces else EMPTY

    def encode(self, texts: Iterable[str | None]) -> list[np.ndarray]:
        """The ids of each text; none for a null."""
        out: list[np.ndarray] = []
        held: list[tuple[int, str, bytes]] = []

        def flush() -> None:
            if not held:
                return
            fine, ids = self._cut(b"".join([raw for _, _, raw in held]), np.cumsum([len(raw) for _, _, raw in held]))
            for (k, text, _), good, found in zip(held, fine.tolist(), ids, strict=True):
                if good:
                    out[k] = found
                elif COMMON.fullmatch(text):
                    out[k] = self._by_pattern(text)
                else:
                    out[k] = self._whole(text)
            held.clear()

        size = 0
        for text in texts:
            out.append(EMPTY)
            if not text:
                continue
            raw = text.encode()
            if any(t in raw for t in self.added) or self.added_lower and any(t in text.lower() for t in self.added_lower):
                out[-1] = self._whole(text)
                continue
            if size + len(raw) > CHUNK:
                flush()
                size = 0
            if len(raw) > CHUNK:
                out[-1] = self._by_pattern(text) if COMMON.fullmatch(text) else self._whole(text)
                continue
            held.append((len(out) - 1, text, raw))
            size += len(raw)
        flush()
        return out


_encoders: dict[str, PieceEncoder] = {}


def encoder(path: str) -> PieceEncoder:
    """One encoder for each file and Python worker, kept from task to task."""
    if path not in _encoders:
        _encoders[path] = PieceEncoder(path)
    return _encoders[path]
