"""SentencePiece BPE encoding by vectorised merge rounds, and decoding.

Texts are cut where no piece of the vocabulary can reach across, and each distinct word of a
batch is encoded once. The words' symbols lie in one flat array, cut into blocks; a word has
as many blocks as its length needs. Each round takes the least pair rank of each word (from
the least ranks of its blocks), merges all leftmost non-overlapping pairs of that rank at the
same time, and links their neighbours; only blocks that hold such pairs are looked at, so a word of any
length goes the same way. Where a merged piece at once forms a better pair, the word's merges
to the right of it wait for a later round, so that the result is always that of merging one
pair at a time. Symbols that are left when no word has a known pair are moved together and spelled.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPACE_MARK = "▁"
NORMAL, USER_DEFINED, UNUSED = 1, 4, 5
CACHE_WORDS = 400_000
#: Symbols of a block.
BLOCK = 256
BATCH_CHARS = 1 << 20


class BpeTables:
    """Pieces, pair ranks and ids of a model, as arrays."""

    def __init__(self, model: bytes):
        import sentencepiece
        from sentencepiece import sentencepiece_model_pb2

        proto = sentencepiece_model_pb2.ModelProto()
        proto.ParseFromString(model)
        norm, train = proto.normalizer_spec, proto.trainer_spec
        pieces = [(p.piece, p.score, p.type) for p in proto.pieces]
        if train.model_type != 2 or norm.precompiled_charsmap or norm.remove_extra_whitespaces or not norm.escape_whitespaces or train.treat_whitespace_as_suffix or any(t in (USER_DEFINED, UNUSED) for _, _, t in pieces):
            raise ValueError("a BPE model is needed that keeps text as it is")
        self.processor = sentencepiece.SentencePieceProcessor(model_proto=model)
        self.dummy_prefix = norm.add_dummy_prefix
        self.bos, self.eos, self.unk = self.processor.bos_id(), self.processor.eos_id(), self.processor.unk_id()
        self.byte_ids = [i for i, (_, _, t) in enumerate(pieces) if t == 6] if train.byte_fallback else None

        normal = {p: i for i, (p, _, t) in enumerate(pieces) if t == NORMAL}
        order = {s: r for r, s in enumerate(sorted({pieces[i][1] for i in normal.values()}, reverse=True))}
        self.strings = list(normal) + sorted({c for p in normal for c in p} - normal.keys())
        self.symbol = {p: k for k, p in enumerate(self.strings)}
        rank = {p: order[pieces[i][1]] for p, i in normal.items()}
        risky = np.zeros(len(order) + 1, bool)
        pairs = {}
        for p in normal:
            for cut in range(1, len(p)):
                a, b = p[:cut], p[cut:]
                if a in self.symbol and b in self.symbol:
                    pairs[self.symbol[a] << 32 | self.symbol[b]] = (rank[p], self.symbol[p])
                    for part in (a, b):
                        if len(part) > 1 and rank[part] >= rank[p]:
                            risky[rank[part]] = True
        self.pairs = pairs
        self.keys = np.array(sorted(pairs), np.int64)
        self.ranks = np.array([pairs[k][0] for k in self.keys.tolist()], np.int64)
        self.merged = np.array([pairs[k][1] for k in self.keys.tolist()], np.int64)
        self.risky, self.none = risky, len(order)
        self.slots = self._hashed()
        self.first_symbol = np.arange(len(self.strings), len(self.strings) + 0x110000, dtype=np.int64)
        for p, k in self.symbol.items():
            if len(p) == 1:
                self.first_symbol[ord(p)] = k
        spelled = [self._ids(p, normal) for p in self.strings]
        self.id_count = np.array([len(x) for x in spelled], np.int64)
        self.id_first = np.array([x[0] for x in spelled], np.uint32)
        self.spelled = spelled
        reach = any(a != SPACE_MARK and b == SPACE_MARK for p in normal for a, b in zip(p, p[1:], strict=False))
        alone = "\n" if not any("\n" in p for p in normal) else ""
        self.words = re.compile(f"{SPACE_MARK}*[^{SPACE_MARK}{alone}]+|{SPACE_MARK}+" + "|\n" * bool(alone)) if not reach else re.compile("(?s).+")

    def _ids(self, s: str, normal: dict) -> list[int]:
        return [normal[s]] if s in normal else [self.byte_ids[b] for b in s.encode("utf-8", "replace")] if self.byte_ids else [self.unk]

    def _hashed(self) -> np.ndarray:
        """Open addressing: each slot holds the place of a key, or -1."""
        self.slot_bits = max(4, int(len(self.keys)).bit_length() + 1)
        slots = np.full(1 << self.slot_bits, -1, np.int64)
        left, at = np.arange(len(self.keys)), self._slot(self.keys)
        while len(left):
            free = slots[at] < 0
            _, one = np.unique(at[free], return_index=True)
            put = np.flatnonzero(free)[one]
            slots[at[put]] = left[put]
            stay = np.ones(len(left), bool)
            stay[put] = False
            left, at = left[stay], (at[stay] + 1) & (len(slots) - 1)
        return slots

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.slot_bits)).astype(np.int64)

    def _find(self, key: np.ndarray) -> np.ndarray:
        """Places of the keys in the table, -1 for those it lacks."""
        slot = self._slot(key)
        found = self.slots[slot]
        look = np.flatnonzero(found >= 0)
        look = look[self.keys[found[look]] != key[look]]
        while len(look):
            slot[look] = (slot[look] + 1) & (len(self.slots) - 1)
            found[look] = self.slots[slot[look]]
            look = look[found[look] >= 0]
            look = look[self.keys[found[look]] != key[look]]
        return found

    def encode_words(self, words: list[str]) -> list[bytes]:
        """The ids of each word, as little-endian unsigned 32-bit integers."""
        if not words:
            return []
        size = np.fromiter(map(len, words), np.int64, len(words))
        left, of = Rounds(self, self._first("".join(words)), size).run()
        ids, count = self._spell(left)
        ends = 4 * np.cumsum(np.bincount(of, weights=count, minlength=len(words)).astype(np.int64))
        blob, a, out = ids.tobytes(), 0, []
        for b in ends.tolist():
            out.append(blob[a:b])
            a = b
        return out

    def _first(self, text: str) -> np.ndarray:
        return self.first_symbol[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")]

    def _spell(self, sym: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of the symbols, and how many each has."""
        known = sym < len(self.id_count)
        low = np.where(known, sym, 0)
        count = self.id_count[low]
        several: dict[int, list[int]] = {}
        for s in np.unique(sym[~known | (count != 1)]).tolist():
            several[s] = self.spelled[s] if s < len(self.spelled) else self._ids(chr(s - len(self.spelled)), {})
            count[sym == s] = len(several[s])
        ends = np.cumsum(count)
        ids = np.empty(int(ends[-1]) if len(ends) else 0, "<u4")
        ids[ends - count] = self.id_first[low]
        for s, values in several.items():
            at = (ends - count)[sym == s]
            for k, v in enumerate(values):
                ids[at + k] = v
        return ids, count

    def rank_of(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ranks of the pairs (a, b), none for unknown ones, and their places in the table."""
        found = self._find(a << 32 | b)
        return np.where(found >= 0, self.ranks[found], self.none), found


class Rounds:
    """Merge rounds over the symbols of many words, laid end to end."""

    def __init__(self, tables: BpeTables, sym: np.ndarray, size: np.ndarray):
        self.t, self.sym, n = tables, sym, len(sym)
        self.word = np.repeat(np.arange(len(size)), size)
        #: neighbours within the word, -1 where it ends
        self.next, self.before = np.arange(1, n + 1), np.arange(-1, n - 1)
        ends = np.cumsum(size)
        self.next[ends[size > 0] - 1] = self.before[(ends - size)[size > 0]] = -1
        self.alive = np.ones(n, bool)
        blocks = -(-size // BLOCK)
        first = np.cumsum(blocks) - blocks
        inside = np.arange(blocks.sum()) - np.repeat(first, blocks)
        self.start = np.repeat(ends - size, blocks) + inside * BLOCK
        self.length = np.minimum(np.repeat(size, blocks) - inside * BLOCK, BLOCK)
        self.block = np.repeat(np.arange(len(self.start)), self.length)
        self.owner = np.repeat(np.arange(int((blocks > 0).sum())), blocks[blocks > 0])
        self.first = first[blocks > 0]
        self.rank, self.place = np.full(n, tables.none), np.full(n, -1)
        self._look(np.arange(n))
        self.least = np.minimum.reduceat(self.rank, self.start) if n else self.rank

    def _look(self, at: np.ndarray) -> None:
        """Ranks of the pairs that begin at these places."""
        nxt = self.next[at]
        some = nxt >= 0
        self.rank[at[~some]] = self.t.none
        at = at[some]
        self.rank[at], self.place[at] = self.t.rank_of(self.sym[at], self.sym[nxt[some]])

    def _places(self, blocks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """All places of the blocks, and where each block begins among them."""
        size = self.length[blocks]
        begin = np.cumsum(size) - size
        return np.repeat(self.start[blocks] - begin, size) + np.arange(size.sum()), begin

    def run(self) -> tuple[np.ndarray, np.ndarray]:
        """The symbols that are left, and the word of each."""
        while len(self.least):
            best = np.minimum.reduceat(self.least, self.first)[self.owner]
            live = np.flatnonzero((self.least == best) & (best < self.t.none))
            if not len(live):
                break
            at, _ = self._places(live)
            i = at[self.rank[at] == np.repeat(best[live], self.length[live])]
            self._merge(self._together(i))
        return self.sym[self.alive], self.word[self.alive]

    def _together(self, i: np.ndarray) -> np.ndarray:
        """Those of the pairs of least rank, in order of place, that one round may merge."""
        joined = np.concatenate([[False], self.next[i[:-1]] == i[1:]])
        run = np.flatnonzero(~joined)
        i = i[(np.arange(len(i)) - np.repeat(run, np.diff(np.append(run, len(i))))) % 2 == 0]
        risky = self.t.risky[self.rank[i]]
        if not risky.any():
            return i
        # what a merge forms with the symbols beside it, those to its left merged before it and those to its right not yet
        new, before, after = self.t.merged[self.place[i]], self.before[i], self.next[self.next[i]]
        near = np.where(before >= 0, self.sym[before], 0)
        merged_too = np.concatenate([[False], self.next[self.next[i[:-1]]] == i[1:]])
        near[1:] = np.where(merged_too[1:], new[:-1], near[1:])
        ours = self.rank[i]
        better = (before >= 0) & (self.t.rank_of(near, new)[0] < ours)
        better |= (after >= 0) & (self.t.rank_of(new, np.where(after >= 0, self.sym[after], 0))[0] < ours)
        better &= risky
        head = np.concatenate([[True], self.word[i[1:]] != self.word[i[:-1]]])
        earlier = np.cumsum(better) - better
        return i[earlier == np.repeat(earlier[head], np.diff(np.append(np.flatnonzero(head), len(i))))]

    def _merge(self, i: np.ndarray) -> None:
        gone = self.next[i]
        after = self.next[gone]
        self.sym[i] = self.t.merged[self.place[i]]
        self.next[i] = after
        self.before[after[after >= 0]] = i[after >= 0]
        self.alive[gone] = False
        self.rank[gone] = self.t.none
        touched = np.zeros(len(self.least), bool)
        before = self.before[i]
        changed = np.concatenate([i, before[before >= 0]])
        self._look(changed)
        touched[self.block[changed]] = touched[self.block[gone]] = True
        blocks = np.flatnonzero(touched)
        at, begin = self._places(blocks)
        self.least[blocks] = np.minimum.reduceat(self.rank[at], begin)


@lru_cache(2)
def tables(model: bytes) -> BpeTables:
    return BpeTables(model)


def encoder(model: bytes):
    """A function from a list of texts to their ids as bytes; keeps words it has met."""
    t = tables(model)
    met: dict[str, bytes] = {}
    head, tail = np.array([t.bos], "<u4").tobytes(), np.array([t.eos], "<u4").tobytes()

    def encode(texts: list[str]) -> list[bytes]:
        if len(met) > CACHE_WORDS:
            met.clear()
        cut = [t.words.findall(((SPACE_MARK if t.dummy_prefix else "") + x).replace(" ", SPACE_MARK)) if x else [] for x in texts]
        new = list({w for words in cut for w in words}.difference(met))
        met.update(zip(new, t.encode_words(new), strict=True))
        return [head + b"".join([met[w] for w in words]) + tail for words in cut]

    return encode


def encode_decode(docs: DataFrame, model: bytes, id_col: str = "doc_id", text_col: str = "text", decode: bool = True) -> DataFrame:
    """(id, ids binary, n_tokens long, decoded string), one row per input row.

    ids are little-endian unsigned 32-bit integers with the begin and end ids; null texts
    count as empty and give just those two. decoded is the library's decoding of the ids.
    Repeated rows give repeated rows; empty tables give empty results.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, processor = encoder(model), tables(model).processor
        for b in batches:
            texts = [x or "" for x in b.column(1).to_pylist()]
            at = 0
            while at < len(texts):
                size, to = 0, at
                while to < len(texts) and (to == at or size + len(texts[to]) <= BATCH_CHARS):
                    size += len(texts[to])
                    to += 1
                ids = encode(texts[at:to])
                back = [processor.decode(np.frombuffer(x, "<u4").tolist()) for x in ids] if decode else [None] * len(ids)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(at, to - at), pa.array(ids, pa.binary()), pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array(back, pa.string())], names=[id_col, "ids", "n_tokens", "decoded"])
                at = to

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"`{id_col}` {kind}, ids binary, n_tokens long, decoded string")


def model_bytes(path: str | None = None) -> bytes:
    """The model file; by default the public 32k piece vocabulary."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("piece_bpe_32k.model")
    with open(path, "rb") as f:
        return f.read()


def token_digests(docs: DataFrame, model: bytes) -> DataFrame:
    coded = encode_decode(docs, model)
    return coded.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2(F.encode("decoded", "utf-8"), 256).alias("decoded_sha256"))


def op4_sentencepiece(spark, sf_dir: str) -> DataFrame:
    return token_digests(spark.read.parquet(f"{sf_dir}/documents.parquet"), model_bytes())
