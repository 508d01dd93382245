"""Byte-level BPE over the distinct words of a slice, all words merged at once in numpy.

Serves tokenizers whose definition drops white space, splits by a fixed pattern and ends words with a
suffix; ids equal the tokenizer library's. Anything else goes to the library itself.
"""

from __future__ import annotations

import unicodedata

import numpy as np
import regex

from tilesieve.llm.bytewords import Powers, words
from tilesieve.llm.common import ship

ship(__name__)

#: Bytes of text hashed at once.
HASHED = 1 << 20
NONE = np.int32(2**31 - 1)
#: The split pattern of such definitions, and the white space that it drops.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
BLANK = "\t-\r\x20\x85\xa0  -     　"


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out = {b: chr(b) for b in plain}
    for n, b in enumerate(x for x in range(256) if x not in out):
        out[b] = chr(256 + n)
    return [out[b] for b in range(256)]


class WordBPE:
    def __init__(self, definition: dict, library):
        """``library`` gives the library's tokenizer, for words that hold an added token."""
        self.library, self.powers = library, Powers()
        model = definition["model"]
        vocab, suffix = model["vocab"], model["end_of_word_suffix"]
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        symbols = byte_symbols()
        self.inner = np.array([vocab[s] for s in symbols], np.int32)
        self.last = np.array([vocab[s + suffix] for s in symbols], np.int32)
        left = np.array([vocab[a] for a, _ in pairs], np.int64)
        right = np.array([vocab[b] for _, b in pairs], np.int64)
        self.product = np.array([vocab[a + b] for a, b in pairs], np.int32)
        self.span = max(vocab.values()) + 1
        first_use = np.full(self.span, len(pairs), np.int64)
        np.minimum.at(first_use, left, np.arange(len(pairs)))
        np.minimum.at(first_use, right, np.arange(len(pairs)))
        #: Merging all occurrences of the best pair at once is right if no merge makes a symbol that an earlier one uses.
        self.orderly = bool((first_use[self.product] > np.arange(len(pairs))).all())
        keys = left * self.span + right
        self.bits = max(16, int(4 * len(keys)).bit_length())
        self.keys = np.full((1 << self.bits) + 64, -1, np.int64)
        self.ranks = np.full((1 << self.bits) + 64, NONE, np.int32)
        for key, rank, slot in zip(keys.tolist(), range(len(keys)), self._slot(keys).tolist(), strict=True):
            while self.keys[slot] >= 0 and self.keys[slot] != key:
                slot += 1
            if self.keys[slot] < 0:
                self.keys[slot], self.ranks[slot] = key, rank
        self.added = [t["content"] for t in definition.get("added_tokens", [])]
        self.pattern = regex.compile(SPLIT.replace(r"\s", BLANK) + "|\n")

    @staticmethod
    def fits(definition: dict) -> bool:
        """Whether the definition is of the kind that this class encodes."""
        normal = (definition.get("normalizer") or {}).get("normalizers") or []
        steps = ((definition.get("pre_tokenizer") or {}).get("pretokenizers")) or []
        model = definition["model"]
        return (
            [n.get("type") for n in normal] == ["NFC", "Replace", "Lowercase"]
            and normal[1].get("pattern") == {"Regex": r"\s+"}
            and normal[1].get("content") == " "
            and [s.get("type") for s in steps] == ["Split", "ByteLevel"]
            and steps[0].get("pattern") == {"Regex": SPLIT}
            and steps[0].get("behavior") == "Removed"
            and bool(steps[0].get("invert"))
            and not steps[1].get("add_prefix_space")
            and not steps[1].get("use_regex")
            and model.get("type") == "BPE"
            and bool(model.get("end_of_word_suffix"))
            and not any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "ignore_merges", "byte_fallback"))
            and all(not (t["lstrip"] or t["rstrip"] or t["single_word"] or t["normalized"]) for t in definition.get("added_tokens", []))
        )

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def _rank(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        keys = left.astype(np.int64) * self.span + right
        slot = self._slot(keys)
        out = np.where(self.keys[slot] == keys, self.ranks[slot], NONE)
        todo = np.flatnonzero((out == NONE) & (self.keys[slot] >= 0))
        while len(todo):
            slot[todo] += 1
            at = slot[todo]
            hit = self.keys[at] == keys[todo]
            out[todo[hit]] = self.ranks[at[hit]]
            todo = todo[~hit & (self.keys[at] >= 0)]
        return out

    def merge(self, data: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of pieces that lie one after another in ``data``: flat ids, and how many each piece has."""
        n = len(lengths)
        counts = np.zeros(n, np.int64)
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        sym = self.inner[data]
        ends = np.cumsum(lengths)
        sym[ends - 1] = self.last[data[ends - 1]]
        word, lens = np.arange(n), lengths.astype(np.int64)
        rank = np.full(len(sym), NONE, np.int32)
        if len(sym) > 1:
            rank[:-1] = self._rank(sym[:-1], sym[1:])
        rank[ends - 1] = NONE
        while len(word):
            starts = np.cumsum(lens) - lens
            best = np.minimum.reduceat(rank, starts)
            done = best == NONE
            if done.any():
                mask = np.repeat(done, lens)
                found.append((word[done], lens[done], sym[mask]))
                sym, rank, word, lens, best = sym[~mask], rank[~mask], word[~done], lens[~done], best[~done]
                if not len(word):
                    break
            flag = rank == np.repeat(best, lens)
            at = np.flatnonzero(flag)
            if len(at) > 1 and (near := np.diff(at) == 1).any():  # runs of one symbol merge from the left
                head = np.concatenate([[True], ~near])
                at = at[(np.arange(len(at)) - np.maximum.accumulate(np.where(head, np.arange(len(at)), 0))) % 2 == 0]
            sym[at] = self.product[rank[at]]
            rank[at] = rank[at + 1]
            keep = np.ones(len(sym), bool)
            keep[at + 1] = False
            owner = np.searchsorted(np.cumsum(lens), at, side="right")
            lens = lens - np.bincount(owner, minlength=len(lens))
            sym, rank = sym[keep], rank[keep]
            at = at - np.arange(len(at))
            last = np.zeros(len(sym) + 1, bool)
            last[np.cumsum(lens) - 1] = True
            mark = np.zeros(len(sym), bool)
            mark[at] = True
            mark[at[at > 0] - 1] = True
            touched = np.flatnonzero(mark & ~last[:-1])
            rank[touched] = self._rank(sym[touched], sym[touched + 1])
            rank[last[:-1]] = NONE
        for w, k, _ in found:
            counts[w] = k
        begin = np.cumsum(counts) - counts
        flat = np.empty(int(counts.sum()), np.uint32)
        for w, k, ids in found:
            flat[np.repeat(begin[w] - (np.cumsum(k) - k), k) + np.arange(len(ids))] = ids
        return flat, counts

    def _distinct(self, items: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of distinct words."""
        text = b"\n".join(items).decode()
        odd = {k for t in self.added if t in text for k, w in enumerate(items) if t.encode() in w}
        if odd:
            text = "\n".join("" if k in odd else w.decode() for k, w in enumerate(items))
        if not text.isascii():
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")
        pieces = self.pattern.findall(text.lower())
        pieces.append("\n")
        known = dict.fromkeys(pieces)
        del known["\n"]
        known = dict(zip(known, range(len(known)), strict=True))
        known["\n"] = -1
        number = np.array(list(map(known.__getitem__, pieces)), np.int64)
        stops = np.flatnonzero(number < 0)
        per = np.diff(stops, prepend=-1) - 1
        number = number[number >= 0]
        del known["\n"]
        raw = "\n".join(known).encode().split(b"\n") if known else []
        sizes = np.fromiter(map(len, raw), np.int64, len(raw))
        flat, counts = self.merge(np.frombuffer(b"".join(raw), np.uint8), sizes) if raw else (np.zeros(0, np.uint32), np.zeros(0, np.int64))
        flat, counts = _gather(flat, counts, number)
        total = np.concatenate([[0], np.cumsum(counts)])
        edge = np.concatenate([[0], np.cumsum(per)])
        out = total[edge[1:]] - total[edge[:-1]]
        if odd:
            ids = np.split(flat, np.cumsum(out)[:-1])
            for k in odd:
                ids[k] = np.array(self.library().encode(items[k].decode(), add_special_tokens=False).ids, np.uint32)
            flat, out = np.concatenate(ids), np.array([len(x) for x in ids], np.int64)
        return flat, out

    def encode(self, data: np.ndarray, begins: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of the texts that begin at ``begins[:-1]`` in ``data``, and how many each has."""
        found, at = [], 0
        while at < len(begins) - 1:  # hashes take eight bytes a byte: a few texts at a time
            to = max(at + 1, int(np.searchsorted(begins, begins[at] + HASHED, side="right")) - 1)
            a, b, owner, h = words(data[begins[at] : begins[to]], begins[at : to + 1] - begins[at], self.powers, fold_case=False)
            found.append(((a + begins[at]).astype(np.int32), (b + begins[at]).astype(np.int32), (owner + at).astype(np.int32), h))
            at = to
        starts, ends, owner, h = (np.concatenate(x) for x in zip(*found, strict=True)) if found else [np.zeros(0, np.int32)] * 4
        found.clear()
        order = np.argsort(h, kind="stable").astype(np.int32)
        h = h[order]
        new = np.concatenate([[True], h[1:] != h[:-1]]) if len(h) else np.zeros(0, bool)
        first = order[new]
        number = np.empty(len(h), np.int32)
        number[order] = np.cumsum(new, dtype=np.int32) - 1
        del h, order, new
        if not len(first):
            return np.zeros(0, np.uint32), np.zeros(len(begins) - 1, np.int64)
        whole = data.tobytes()
        flat, counts = self._distinct([whole[a:b] for a, b in zip(starts[first].tolist(), ends[first].tolist(), strict=True)])
        ids, per = _gather(flat, counts, number)
        return ids, np.bincount(owner, per, len(begins) - 1).astype(np.int64)


def _gather(flat: np.ndarray, counts: np.ndarray, number: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The runs of ``flat`` that ``number`` names, one after another."""
    begin = np.cumsum(counts) - counts
    per = counts[number]
    shift = np.cumsum(per) - per
    small = np.int32 if len(per) and int(shift[-1]) + int(per[-1]) < 2**31 - 1 else np.int64
    at = np.repeat((begin[number] - shift).astype(small), per)
    at += np.arange(len(at), dtype=small)
    return flat[at], per
