"""Token counts by heap-and-linked-list pair merging, and cached token ids.

Both work on pieces between ASCII white space.  For a tokenizer that drops white
space no token crosses such a piece, so a piece is tokenized once per worker and
then found in a bounded cache.  Null text counts as empty; a text without words
has no tokens; rows with equal doc_id are counted each on its own, null doc_ids stay
null, empty tables give no rows and other columns are not looked at.  Texts are taken
whole, one batch of them in memory at a time.
"""

from __future__ import annotations

import heapq
import json
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LONGEST, HashCache, id_and_bytes, piece_hashes, slices, words_of

#: a control character that stands between pieces that are tokenized together
MARK = b"\x01"
_loaded: dict[str, object] = {}


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    hidden = iter(range(256, 512))
    return [chr(b) if b in set(shown) else chr(next(hidden)) for b in range(256)]


class PairMerger:
    """Counts the tokens of a piece of text: symbols minus merges.

    ``path`` is a tokenizers JSON file with a byte-level BPE model.  Normaliser
    and splitter are the library's own; for the characters below U+0180 (without
    controls) they are replaced by an equal, quicker pattern.
    """

    #: fixed values: contractions and classes of the splitter, below U+0180
    SIMPLE = re.compile("[\x21-\x7e\xa1-\xac\xae-ſ]*")
    SPLIT = re.compile("[a-z\xaa\xb5\xba\xdf-\xf6\xf8-ſ]+|'(?:s|t|re|ve|m|ll|d)|[0-9\xb2\xb3\xb9\xbc-\xbe]|(?:(?!'(?:s|t|re|ve|m|ll|d))[^a-z\xaa\xb5\xba\xdf-\xf6\xf8-ſ0-9\xb2\xb3\xb9\xbc-\xbe])(?:[^a-z\xaa\xb5\xba\xdf-\xf6\xf8-ſ0-9\xb2\xb3\xb9\xbc-\xbe])*")

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        if model["type"] != "BPE" or model.get("byte_fallback") or model.get("ignore_merges"):
            raise ValueError("a byte-level BPE model is needed")
        self.suffix = model.get("end_of_word_suffix") or ""
        self.rank = {tuple(p if isinstance(p, list) else p.split(" ")): k for k, p in enumerate(model["merges"])}
        self.symbols = byte_symbols()
        self.library = Tokenizer.from_file(path)
        special = [re.escape(t["content"]) for t in spec["added_tokens"]]
        self.special = re.compile("|".join(special)) if special else None
        split = str(spec["pre_tokenizer"])
        #: only then does no token hold white space
        self.drops_space = "'invert': True" in split and "'behavior': 'Removed'" in split
        self.quick = self.drops_space and self.suffix == "</w>"

    def merges(self, symbols: list[str]) -> int:
        """How many merges end with no ranked adjacent pair left."""
        n = len(symbols)
        if n < 2:
            return 0
        rank = self.rank
        after = list(range(1, n + 1))
        before = list(range(-1, n - 1))
        heap = [(r, i, symbols[i], symbols[i + 1]) for i in range(n - 1) if (r := rank.get((symbols[i], symbols[i + 1]))) is not None]
        heapq.heapify(heap)
        done = 0
        while heap:
            _, i, left, right = heapq.heappop(heap)
            j = after[i]
            if j >= n or symbols[i] is not left or symbols[j] is not right:
                continue  # one side was merged meanwhile
            symbols[i] = joined = left + right
            symbols[j] = ""
            k = after[i] = after[j]
            done += 1
            if k < n:
                before[k] = i
                if (r := rank.get((joined, symbols[k]))) is not None:
                    heapq.heappush(heap, (r, i, joined, symbols[k]))
            if (h := before[i]) >= 0 and (r := rank.get((symbols[h], joined))) is not None:
                heapq.heappush(heap, (r, h, symbols[h], joined))
        return done

    def piece(self, symbols: list[str]) -> int:
        if self.suffix:
            symbols[-1] += self.suffix
        return len(symbols) - self.merges(symbols)

    def plain(self, text: str) -> int:
        if self.quick and self.SIMPLE.fullmatch(text):
            table = self.symbols
            return sum(self.piece([table[b] for b in word.encode()]) for word in self.SPLIT.findall(text.lower()))
        text = self.library.normalizer.normalize_str(text) if self.library.normalizer else text
        return sum(self.piece(list(word)) for word, _ in self.library.pre_tokenizer.pre_tokenize_str(text) if word)

    def count(self, raw: bytes) -> int:
        text = raw.decode("utf-8", "replace")
        if self.special is None or not self.special.search(text):
            return self.plain(text)
        total = last = 0
        for m in self.special.finditer(text):
            total += self.plain(text[last : m.start()]) + 1
            last = m.end()
        return total + self.plain(text[last:])


def merger(path: str) -> tuple[PairMerger, HashCache]:
    if path not in _loaded:
        m = PairMerger(path)
        _loaded[path] = (m, HashCache(m.count))
    return _loaded[path]


def count_tokens(docs: DataFrame, path: str, limit: int = 2048) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for each row of ``docs``.

    Whole texts, no shuffle: one pass over the scan, with a cache per worker.
    """

    def counts(batches):
        m, cache = merger(path)
        get = cache.__getitem__
        for batch in slices(batches):
            texts = batch.column(1).to_pylist()
            found = [sum(map(get, t.split())) if m.drops_space else m.count(t) for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(t) for t in texts], pa.int64()), pa.array(found, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    out = id_and_bytes(docs).mapInArrow(counts, "doc_id long, n_bytes long, n_tokens long")
    return out.withColumn("over_limit", F.col("n_tokens") > F.lit(limit))


class PairTable:
    """Ranked pairs of symbol ids, looked up for whole arrays.

    A pair's key is hashed into a first table; the few keys whose place is taken
    are in a second one without collisions.
    """

    def __init__(self, pairs: np.ndarray, merged: np.ndarray, size: int):
        self.size = np.int64(size)
        self.key = np.append(pairs[:, 0] * self.size + pairs[:, 1], -1)
        self.rank = np.append(np.arange(len(pairs)), NO_RANK)
        self.merged = np.append(merged, -1)
        self.first, at = np.full(1 << 20, len(pairs), np.int32), self.place(self.key[:-1], FIRST, 20)
        self.first[at[::-1]] = np.arange(len(pairs))[::-1]  # the earliest pair keeps the place
        late = np.flatnonzero(self.first[at] != np.arange(len(pairs)))
        self.taken = np.zeros(1 << 20, bool)
        self.taken[at[late]] = True
        self.factor = SECOND
        while len(np.unique(self.place(self.key[late], self.factor, 22))) < len(late):
            self.factor = self.factor * FIRST + np.uint64(2)
        self.second = np.full(1 << 22, len(pairs), np.int32)
        self.second[self.place(self.key[late], self.factor, 22)] = late

    @staticmethod
    def place(key: np.ndarray, factor: np.uint64, bits: int) -> np.ndarray:
        return (key.astype(np.uint64) * factor >> np.uint64(64 - bits)).astype(np.int64)

    def find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Numbers of the pairs, or the number of no pair."""
        key = left * self.size + right
        at = self.place(key, FIRST, 20)
        found = self.first[at]
        miss = np.flatnonzero(self.key[found] != key)
        again = miss[self.taken[at[miss]]]
        found[miss] = len(self.key) - 1
        if len(again):
            other = self.second[self.place(key[again], self.factor, 22)]
            found[again] = np.where(self.key[other] == key[again], other, len(self.key) - 1)
        return found


#: fixed values: odd multipliers of the two tables; the rank of no pair
FIRST, SECOND = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)
NO_RANK = 1 << 30
#: bytes that plain pieces (up to U+017F, no controls) don't have
STRANGE = np.ones(256, bool)
STRANGE[0x21:0x7F] = STRANGE[0x80:0xC0] = STRANGE[0xC2:0xC6] = False


def merge_all(symbols: np.ndarray, starts: np.ndarray, table: PairTable) -> tuple[np.ndarray, np.ndarray]:
    """Merges many words at once: in each round, every word's lowest-ranked leftmost pair.

    ``symbols`` are the words' symbol ids one after the other, ``starts`` where each
    begins.  Returns the merged ids and the words' new starts.  Words that have no
    pair left leave the rounds.
    """
    done_ids, done_words = [], []
    word = np.arange(len(starts))
    lens = np.diff(np.append(starts, len(symbols)))
    symbols = symbols.astype(np.int64)

    def ranks(at: np.ndarray, last: np.ndarray) -> np.ndarray:
        """Pair numbers at places that aren't the last of their word."""
        out = np.full(len(at), len(table.key) - 1, np.int64)
        inner = ~last
        out[inner] = table.find(symbols[at[inner]], symbols[at[inner] + 1])
        return out

    final = np.zeros(len(symbols), bool)
    final[np.cumsum(lens) - 1] = True
    pair = ranks(np.arange(len(symbols)), final)
    while len(word):
        begin = np.cumsum(lens) - lens
        order = table.rank[pair] << 32 | np.arange(len(pair))
        best = np.minimum.reduceat(order, begin)
        live = best >> 32 < NO_RANK
        if not live.all():
            stays = np.repeat(live, lens)
            done_ids.append(symbols[~stays])
            done_words.append((word[~live], lens[~live]))
            number = np.cumsum(stays) - 1
            symbols, pair, final = symbols[stays], pair[stays], final[stays]
            word, lens, best = word[live], lens[live], best[live]
            if not len(word):
                break
            at = number[best & 0xFFFFFFFF]
        else:
            at = best & 0xFFFFFFFF
        symbols[at] = table.merged[pair[at]]
        final[at] |= final[at + 1]
        keep = np.ones(len(symbols), bool)
        keep[at + 1] = False
        at = at - np.arange(len(at))  # one symbol went from each word before
        symbols, pair, final = symbols[keep], pair[keep], final[keep]
        lens = lens - 1
        pair[at] = ranks(at, final[at])
        inside = at > np.cumsum(lens) - lens
        left = at[inside] - 1
        pair[left] = table.find(symbols[left], symbols[left + 1])
    ids = np.concatenate(done_ids) if done_ids else symbols
    order = np.concatenate([w for w, _ in done_words]) if done_words else word
    sizes = np.concatenate([n for _, n in done_words]) if done_words else lens
    # back into the order of the words
    out_lens = np.empty(len(starts), np.int64)
    out_lens[order] = sizes
    out_starts = np.cumsum(out_lens) - out_lens
    out = np.empty(len(ids), np.int64)
    out[np.arange(len(ids)) - np.repeat(np.cumsum(sizes) - sizes, sizes) + np.repeat(out_starts[order], sizes)] = ids
    return out, out_starts


class IdCache:
    """Ids of texts, piece by piece, in arrays.

    The texts of a batch are cut at ASCII white space; equal pieces are found by a
    64-bit hash and looked up in a sorted table of the pieces this worker has met.
    New pieces of plain characters are merged together (``merge_all``); others, and
    tokenizers that keep white space, go through the library.  Both give the
    library's ids.
    """

    def __init__(self, path: str, limit: int = 2_000_000):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        self.rules, self.limit = PairMerger(path), limit
        self.library = self.rules.library
        if not self.rules.quick:
            return
        vocab, suffix, symbols = self.library.get_vocab(), self.rules.suffix, self.rules.symbols
        self.inner, self.last = (np.array([vocab[c + x] for c in symbols]) for x in ("", suffix))
        ranked = sorted(self.rules.rank, key=self.rules.rank.get)
        self.table = PairTable(np.array([(vocab[a], vocab[b]) for a, b in ranked], np.int64), np.array([vocab[a + b] for a, b in ranked], np.int64), len(vocab) + 2)
        self.mark = int(self.last[MARK[0]])
        self.forget()

    def forget(self) -> None:
        self.key, self.begin, self.size, self.ids = np.empty(0, np.uint64), np.empty(0, np.int64), np.empty(0, np.int32), np.empty(0, np.uint16 if len(self.inner) and self.library.get_vocab_size() < 2**16 else np.uint32)

    def encode(self, texts: list[bytes]) -> list[bytes]:
        """The ids of each text, without added tokens."""
        from array import array

        if not self.rules.quick:
            return [array("I", e.ids).tobytes() for e in self.library.encode_batch_fast([t.decode("utf-8", "replace") for t in texts], add_special_tokens=False)]
        buf = b"\n".join(texts) + b"\n"
        data = np.frombuffer(buf, np.uint8)
        start, end = words_of(data, np.empty(0, np.int64))
        if not len(start):
            return [b""] * len(texts)
        key = piece_hashes(buf, data, start, end)
        pieces, first, number = np.unique(key, return_index=True, return_inverse=True)
        if len(self.key) > self.limit:
            self.forget()
        at = np.minimum(np.searchsorted(self.key, pieces), max(len(self.key) - 1, 0))
        new = self.key[at] != pieces if len(self.key) else np.ones(len(pieces), bool)
        if new.any():
            self.learn(buf, data, pieces[new], start[first[new]], end[first[new]])
            at = np.searchsorted(self.key, pieces)
        size = self.size[at][number].astype(np.int64)
        stop = np.cumsum(size)
        place = np.arange(stop[-1]) + np.repeat(self.begin[at][number] - (stop - size), size)
        ids = self.ids[place].astype("<u4").tobytes()
        edge = np.cumsum([len(t) + 1 for t in texts])
        upto = 4 * np.concatenate([[0], stop])[np.searchsorted(start, edge)]
        return [ids[a:b] for a, b in zip([0, *upto[:-1].tolist()], upto.tolist(), strict=True)]

    def learn(self, buf: bytes, data, key, start, end) -> None:
        """Adds pieces to the table, sorted by key."""
        size = end - start
        source = np.repeat(start, size) + np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)
        flat = data[source]
        after = np.append(flat[1:], 0)
        strange = STRANGE[flat] | ((flat == 0xC2) & ((after <= 0xA0) | (after == 0xAD))) | ((flat == ord("<")) & (after == ord("|")))
        odd = np.logical_or.reduceat(strange, np.cumsum(size) - size) | (size > LONGEST)
        ids, begin, length = [], np.zeros(len(key), np.int64), np.zeros(len(key), np.int64)
        plain = np.flatnonzero(~odd)
        if len(plain):
            mine, n = size[plain], len(plain)
            room = mine + 3
            text = np.full(int(room.sum()) - 3, 32, np.uint8)
            to = np.cumsum(room) - room
            text[np.repeat(to, mine) + np.arange(int(mine.sum())) - np.repeat(np.cumsum(mine) - mine, mine)] = flat[~np.repeat(odd, size)]
            text[to[1:] - 2] = MARK[0]
            raw = np.frombuffer(" ".join(self.rules.SPLIT.findall(text.tobytes().decode().lower())).encode(), np.uint8)
            space = raw == 32
            last = np.append(space[1:], True) & ~space
            symbols = np.where(last, self.last[raw], self.inner[raw])[~space]
            starts = np.flatnonzero(np.concatenate([[True], last[~space][:-1]]))
            merged, _ = merge_all(symbols, starts, self.table)
            cuts = np.flatnonzero(merged == self.mark)
            begin[plain] = np.concatenate([[0], cuts + 1])
            length[plain] = np.concatenate([cuts, [len(merged)]]) - begin[plain]
            ids.append(merged)
        at = len(ids[0]) if ids else 0
        strange = np.flatnonzero(odd).tolist()
        texts = [buf[start[i] : end[i]].decode("utf-8", "replace") for i in strange]
        for i, e in zip(strange, texts and self.library.encode_batch_fast(texts, add_special_tokens=False), strict=True):
            ids.append(np.array(e.ids, np.int64))
            begin[i], length[i] = at, len(e.ids)
            at += len(e.ids)
        begin += len(self.ids)
        self.ids = np.concatenate([self.ids, *[x.astype(self.ids.dtype) for x in ids]])
        where = np.searchsorted(self.key, key)
        self.key, self.begin, self.size = np.insert(self.key, where, key), np.insert(self.begin, where, begin), np.insert(self.size, where, length.astype(np.int32))


def id_cache(path: str) -> IdCache:
    key = f"ids:{path}"
    if key not in _loaded:
        _loaded[key] = IdCache(path)
    return _loaded[key]
