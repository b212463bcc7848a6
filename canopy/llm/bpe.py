"""BPE encoding and decoding with a segment tree over adjacent pair ranks.

Leaf i holds the rank of the pair that starts at symbol i, joined with i; an inner node holds the lesser
of its children. The root is thus the leftmost pair of lowest rank. A merge changes three leaves, each
repaired in a logarithmic number of steps, and the word is done when the root holds no rank.

Many short words are merged side by side, one row of a numpy tree each; few or long ones by a list tree.
"""

from __future__ import annotations

import hashlib
import json
import unicodedata
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame

from canopy.llm.common import ship

NONE = np.iinfo(np.int64).max
#: Words remembered by a worker; past it the memory is emptied, which costs time and changes nothing.
CACHE_WORDS = 400_000
SIDE_BY_SIDE = 24
LONG = 256
#: White space as the vocabulary's normaliser sees it.
BLANK = regex.compile("\\p{White_Space}+")
#: Python's split() also breaks at these, which are no white space to the normaliser.
ODD = regex.compile("[\x1c-\x1f]")


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte: itself where printable, else the next unused code from 256 on."""
    printable = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in printable else chr(next(spare)) for b in range(256)]


class Vocabulary:
    """What a tokenizer file of this kind says, and the words merged so far."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            said = json.load(f)
        model = said["model"]
        self.suffix = model["end_of_word_suffix"] or ""
        self.ids: dict[str, int] = model["vocab"]
        self.added = {x["content"]: x["id"] for x in said["added_tokens"]}
        self.names = {i: t for t, i in [*self.ids.items(), *self.added.items()]}
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        width = max(max(self.ids.values()), 1) + 1
        self.width = width
        keys = np.array([self.ids[a] * width + self.ids[b] for a, b in pairs], dtype=np.int64)
        made = np.array([self.ids[a + b] for a, b in pairs], dtype=np.int64)
        order = np.argsort(keys, kind="stable")
        order = order[np.append(keys[order][1:] != keys[order][:-1], True)]  # a pair given twice: the last holds
        self.keys, self.ranks, self.made = keys[order], order.astype(np.int64), made[order]
        self.rank_of = dict(zip(self.keys.tolist(), zip(self.ranks.tolist(), self.made.tolist())))
        letters = byte_letters()
        self.inner = [self.ids.get(c, -1) for c in letters]
        self.final = [self.ids.get(c + self.suffix, -1) for c in letters]
        split = [p["pattern"]["Regex"] for p in said["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split"]
        self.pieces = regex.compile(split[0].replace("\\s", "\\p{White_Space}"))
        self.special = regex.compile("(" + "|".join(map(regex.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        #: by stretch of text between blanks: its ids and its tokens, each joined by spaces
        self.known: dict[str, tuple[str, str]] = {}
        #: the same by word
        self.words: dict[str, tuple[str, str]] = {}
        self.digits = {i: str(i) for i in self.names}

    def look(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank (NONE if no merge) and result of each pair key."""
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        hit = self.keys[at] == keys
        return np.where(hit, self.ranks[at], NONE), self.made[at]

    def symbols(self, word: str) -> list[int]:
        raw = word.encode()
        out = [self.inner[b] for b in raw[:-1]] + [self.final[raw[-1]]]
        return [x for x in out if x >= 0]

    def merge_one(self, sym: list[int]) -> list[int]:
        n = len(sym)
        if n < 2:
            return sym
        size = 1 << (n - 1).bit_length()
        tree = [NONE] * (2 * size)
        get, width = self.rank_of.get, self.width

        def leaf(i: int, j: int) -> int:
            r = get(sym[i] * width + sym[j])
            return NONE if r is None else r[0] * size + i

        for i in range(n - 1):
            tree[size + i] = leaf(i, i + 1)
        for k in range(size - 1, 0, -1):
            tree[k] = min(tree[2 * k], tree[2 * k + 1])
        after, before = [*range(1, n + 1)], [*range(-1, n - 1)]

        def put(i: int, value: int) -> None:
            k = size + i
            tree[k] = value
            k >>= 1
            while k:
                tree[k] = min(tree[2 * k], tree[2 * k + 1])
                k >>= 1

        while (root := tree[1]) != NONE:
            i = root % size
            j = after[i]
            sym[i] = get(sym[i] * width + sym[j])[1]
            k = after[i] = after[j]
            put(j, NONE)
            if k < n:
                before[k] = i
                put(i, leaf(i, k))
            else:
                put(i, NONE)
            if (h := before[i]) >= 0:
                put(h, leaf(h, i))
        out, i = [], 0
        while i < n:
            out.append(sym[i])
            i = after[i]
        return out

    def merge_many(self, rows: list[list[int]]) -> list[list[int]]:
        """Rows of two symbols and more, of like length."""
        m, most = len(rows), max(map(len, rows))
        size = 1 << (most - 1).bit_length()
        length = np.fromiter(map(len, rows), np.int64, m)
        sym = np.full((m, size + 1), -1, dtype=np.int64)
        sym[np.arange(size + 1) < length[:, None]] = np.fromiter((x for r in rows for x in r), np.int64, int(length.sum()))
        tree = np.full((m, 2 * size), NONE, dtype=np.int64)
        place = np.arange(size)
        pair = sym[:, :-1] * self.width + sym[:, 1:]
        ok = place < (length - 1)[:, None]
        rank = np.full(pair.shape, NONE, dtype=np.int64)
        rank[ok] = self.look(pair[ok])[0]
        tree[:, size:] = np.where(rank == NONE, NONE, rank * size + place)
        k = size
        while k > 1:
            tree[:, k // 2 : k] = np.minimum(tree[:, k : 2 * k : 2], tree[:, k + 1 : 2 * k : 2])
            k //= 2
        after = np.broadcast_to(np.arange(1, size + 2), (m, size + 1)).copy()
        before = np.broadcast_to(np.arange(-1, size), (m, size + 1)).copy()
        dead = np.zeros((m, size + 1), dtype=bool)

        def put(r: np.ndarray, i: np.ndarray, value: np.ndarray) -> None:
            k = size + i
            tree[r, k] = value
            while size > 1 and k[0] > 1:
                k = k >> 1
                tree[r, k] = np.minimum(tree[r, 2 * k], tree[r, 2 * k + 1])

        def leaf(r: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
            rank, _ = self.look(sym[r, i] * self.width + sym[r, j])
            return np.where(rank == NONE, NONE, rank * size + i)

        live = np.flatnonzero(tree[:, 1] != NONE)
        while len(live):
            i = tree[live, 1] % size
            j = after[live, i]
            sym[live, i] = self.look(sym[live, i] * self.width + sym[live, j])[1]
            k = after[live, j]
            after[live, i] = k
            dead[live, j] = True
            put(live, j, np.full(len(live), NONE))
            more = k < length[live]
            before[live[more], k[more]] = i[more]
            new = np.full(len(live), NONE)
            new[more] = leaf(live[more], i[more], k[more])
            put(live, i, new)
            h = before[live, i]
            has = h >= 0
            if has.any():
                put(live[has], h[has], leaf(live[has], h[has], i[has]))
            live = live[tree[live, 1] != NONE]
        left = ~dead[:, :-1] & (place < length[:, None])
        flat, ends = sym[:, :-1][left].tolist(), np.cumsum(left.sum(1)).tolist()
        return [flat[a:b] for a, b in zip([0, *ends], ends)]

    def merged(self, fresh: list[str]) -> dict[str, list[int]]:
        """The ids of each word."""
        by_size: dict[int, list[tuple[str, list[int]]]] = {}
        out: dict[str, list[int]] = {}
        for w in fresh:
            s = self.symbols(w)
            by_size.setdefault((len(s) - 1).bit_length() if len(s) > 1 else -1, []).append((w, s))
        for bits, group in by_size.items():
            if bits < 0:
                out.update(group)
            elif len(group) < SIDE_BY_SIDE or 1 << bits > LONG:
                out.update((w, self.merge_one(s)) for w, s in group)
            else:
                step = max(1, (1 << 18) >> bits)
                for a in range(0, len(group), step):
                    part = group[a : a + step]
                    out.update(zip((w for w, _ in part), self.merge_many([s for _, s in part])))
        return out

    def learn(self, fresh: list[str]) -> None:
        """Encode and remember stretches. No piece of the splitting pattern holds a blank, and no composition crosses one, so each stretch is encoded alone."""
        cut = [self.pieces.findall(unicodedata.normalize("NFC", w).replace("Σ", "σ").lower()) for w in fresh]  # a capital sigma has one lower-case form here
        if len(self.words) > CACHE_WORDS:
            self.words.clear()
        new = {p for c in cut for p in c}
        new -= self.words.keys()
        digits, names, words = self.digits.__getitem__, self.names.__getitem__, self.words
        for p, ids in self.merged(list(new)).items():
            words[p] = (" ".join(map(digits, ids)), " ".join(map(names, ids)))
        for w, c in zip(fresh, cut):
            self.known[w] = words[c[0]] if len(c) == 1 else (" ".join([words[p][0] for p in c]), " ".join([words[p][1] for p in c]))

    def stretches(self, text: str) -> list[str]:
        """The text between blanks; a special token stands by itself, after a blank that no stretch begins with."""
        if self.special is None or "<|" not in text or not (parts := self.special.split(text))[1:]:
            return BLANK.sub(" ", text).split(" ") if ODD.search(text) else text.split()
        return [w for k, part in enumerate(parts) for w in ([" " + part] if k % 2 else self.stretches(part))]

    def encode(self, texts: list[str]) -> list[tuple[str, str, int]]:
        """Ids joined by spaces, decoded text and number of ids of each text."""
        cut = [[w for w in s if w] if "" in (s := self.stretches(t)) else s for t in texts]
        if len(self.known) > CACHE_WORDS:
            self.known.clear()
        get = self.known.get
        found = [[*map(get, words)] for words in cut]
        fresh = {w for words, got in zip(cut, found) if None in got for w, x in zip(words, got) if x is None}
        for w in [w for w in fresh if w[0] == " "]:
            fresh.discard(w)
            self.known[w] = (str(self.added[w[1:]]), w[1:])
        if fresh:
            self.learn(list(fresh))
        out = []
        for words, got in zip(cut, found):
            if None in got:
                got = [*map(get, words)]
            said = " ".join([x[0] for x in got])
            out.append((said, " ".join([x[1] for x in got]), said.count(" ") + 1 if said else 0))
        return out


@lru_cache(maxsize=2)
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


def decode(vocab: Vocabulary, ids: list[int]) -> str:
    """The file names no decoder: tokens joined by single spaces, special ones kept."""
    return " ".join(vocab.names[i] for i in ids if i in vocab.names)


COLUMNS = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def encode_documents(docs: DataFrame, path: str) -> DataFrame:
    """Digests of each text's ids and of the text decoded from them.

    Null and empty texts have no ids and decode to the empty text. Other columns are ignored.
    """
    ship(docs.sparkSession)

    def run(batches):
        vocab = vocabulary(path)
        for batch in batches:
            ids, texts = batch.column("doc_id"), pc.fill_null(batch.column("text"), "").to_pylist()
            rows, part, size = [], [], 0
            for i, t in enumerate(texts):
                part.append(t)
                size += len(t)
                if size > 1 << 20 or i + 1 == len(texts):
                    rows += vocab.encode(part)
                    part, size = [], 0
            digest = lambda s: hashlib.sha256(s.encode()).hexdigest()
            yield pa.RecordBatch.from_arrays(
                [ids.cast(pa.int64()), pa.array([r[2] for r in rows], pa.int64()), pa.array([digest(r[0]) for r in rows], pa.string()), pa.array([digest(r[1]) for r in rows], pa.string())],
                ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    return docs.select("doc_id", "text").mapInArrow(run, COLUMNS)
