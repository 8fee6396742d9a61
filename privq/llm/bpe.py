"""Byte-level BPE encoding and decoding with a segment tree over adjacent pair ranks.

``merge_symbols`` keeps one leaf for each adjacent pair of a pre-token. A leaf holds ``rank * size + position``, so the
root is the leftmost pair of lowest rank; a merge touches three leaves and their ancestors only. A text is cut into
chunks before each blank that stands between two other characters. There the pre-token pattern always ends a token, so
a chunk can be encoded alone and remembered. A text where that rule can't be applied (several blanks in a row, a blank
at its end, other white space after a blank) goes through the pattern as a whole.

Null text counts as empty and has no tokens; equal texts give equal rows; other columns of the input are not read.
"""

from __future__ import annotations

import hashlib
import json
from array import array
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privq.llm.common import table, text_or_empty, tidy

#: Fixed value: the pre-token pattern of the byte-level vocabulary.
PRETOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Ranges of code points that ``regex`` counts among letters or numbers and the library doesn't.
NEWER = (
    (0x558, 0x558), (0x58B, 0x58C), (0x88F, 0x88F), (0xC5C, 0xC5C), (0xCDC, 0xCDC), (0x208F, 0x208F), (0x209D, 0x209F), (0xA7CE, 0xA7CF), (0xA7D2, 0xA7D2), (0xA7D4, 0xA7D4), (0xA7DD, 0xA7DD), (0xA7E2, 0xA7E2), (0xA7F1, 0xA7F1), (0xAB6C, 0xAB6D),
    (0x107BB, 0x107BF), (0x10940, 0x10959), (0x10EC5, 0x10EC7), (0x10ED9, 0x10EEE), (0x11B0A, 0x11B0A), (0x11DB0, 0x11DDB), (0x11DE0, 0x11DE9), (0x11DF1, 0x11DF1), (0x1246F, 0x1246F), (0x12475, 0x1247F), (0x12550, 0x12686), (0x16EA0, 0x16EB8), (0x16EBB, 0x16ED3),
    (0x16FF2, 0x16FF6), (0x187F8, 0x187FF), (0x18CD6, 0x18CDA), (0x18D09, 0x18D20), (0x18D80, 0x18DF2), (0x18E00, 0x19191), (0x191A0, 0x191D2), (0x1B123, 0x1B128), (0x1B168, 0x1B168), (0x1D6A6, 0x1D6A6), (0x1DF1F, 0x1DF24), (0x1DF2B, 0x1DF81), (0x1DF90, 0x1DF96),
    (0x1DFCD, 0x1DFFF), (0x1E6C0, 0x1E6DE), (0x1E6E0, 0x1E6E2), (0x1E6E4, 0x1E6E5), (0x1E6E7, 0x1E6ED), (0x1E6F0, 0x1E6F4), (0x1E6FE, 0x1E6FF), (0x2B73A, 0x2B73F), (0x2B81E, 0x2B81E), (0x2CEA2, 0x2CEAD), (0x323B0, 0x33479), (0x3D000, 0x3FC3F),
)
CACHE_ENTRIES = 250_000
_SPACE = regex.compile(r"\s")
_RARE = "".join(f"{chr(a)}-{chr(b)}" for a, b in NEWER)
_HAS_RARE = regex.compile(f"[{_RARE}]")
#: Marks that are a pre-token of their own behind a word, and the end of the code points whose letters all versions share.
_ENDS, _SETTLED = frozenset(".,;:!?"), "\u0250"
_NONE = 1 << 62


def byte_alphabet() -> dict[str, int]:
    """Printable stand-in of each byte: itself where printable, else the next free code point from 256 on."""
    shown = {b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255}
    hidden = [b for b in range(256) if b not in shown]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


class Vocabulary:
    """Ids, merge ranks and bytes of a tokenizer file in the JSON form."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        alphabet, ids = byte_alphabet(), spec["model"]["vocab"]
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.byte_id = [0] * 256
        for shown, b in alphabet.items():
            self.byte_id[b] = ids[shown]
        self.rank: dict[int, int] = {}
        self.merged: list[int] = []
        for pair in spec["model"]["merges"]:
            left, right = pair if isinstance(pair, list) else pair.split(" ")
            self.rank[ids[left] << 20 | ids[right]] = len(self.merged)
            self.merged.append(ids[left + right])
        self.bytes_of = {i: bytes(alphabet[c] for c in t) for t, i in ids.items() if t not in self.special}
        self.bytes_of |= {i: t.encode() for t, i in self.special.items()}

    def encode_word(self, word: bytes) -> list[int]:
        return merge_symbols([self.byte_id[b] for b in word], self.rank, self.merged)

    def decode(self, ids: list[int]) -> str:
        return b"".join([self.bytes_of[i] for i in ids]).decode("utf-8", "replace")


def merge_symbols(symbols: list[int], rank: dict[int, int], merged: list[int]) -> list[int]:
    """Merge the leftmost pair of lowest rank until no adjacent pair has a rank."""
    n = len(symbols)
    if n < 2:
        return symbols
    size = 1 << (n - 1).bit_length()
    tree = [_NONE] * (2 * size)
    for i in range(n - 1):
        r = rank.get(symbols[i] << 20 | symbols[i + 1])
        if r is not None:
            tree[size + i] = r * size + i
    for k in range(size - 1, 0, -1):
        a, b = tree[2 * k], tree[2 * k + 1]
        tree[k] = a if a < b else b
    after, before = list(range(1, n + 1)), list(range(-1, n - 1))

    def put(leaf: int, key: int) -> None:
        k = size + leaf
        tree[k] = key
        k >>= 1
        while k:
            a, b = tree[2 * k], tree[2 * k + 1]
            low = a if a < b else b
            if tree[k] == low:
                return
            tree[k] = low
            k >>= 1

    while (key := tree[1]) != _NONE:
        r, i = divmod(key, size)
        gone = after[i]
        symbols[i] = merged[r]
        symbols[gone] = -1
        nxt = after[gone]
        after[i] = nxt
        put(gone, _NONE)
        if nxt < n:
            before[nxt] = i
            q = rank.get(symbols[i] << 20 | symbols[nxt])
            put(i, _NONE if q is None else q * size + i)
        else:
            put(i, _NONE)
        if (p := before[i]) >= 0:
            q = rank.get(symbols[p] << 20 | symbols[i])
            put(p, _NONE if q is None else q * size + p)
    return [s for s in symbols if s >= 0]


def packed(ids: list[int]) -> bytes:
    """Ids as 32-bit words: what is remembered of a word takes a third of a list's memory."""
    return array("i", ids).tobytes()


def unpacked(words: bytes) -> list[int]:
    return memoryview(words).cast("i").tolist()


class WordBatch:
    """The same merges for many words at once: one segment tree a row, one numpy step for a merge of every word."""

    def __init__(self, vocabulary: Vocabulary):
        pairs = np.fromiter(vocabulary.rank, np.int64, len(vocabulary.rank))
        ranks = np.fromiter(vocabulary.rank.values(), np.int64, len(pairs))
        order = np.argsort(pairs)
        self.pairs, self.ranks, self.merged = pairs[order], ranks[order], np.array(vocabulary.merged, np.int64)
        self.byte_id = np.array(vocabulary.byte_id, np.int64)
        both = self.byte_id[:, None] << 20 | self.byte_id[None, :]
        self.byte_pair_rank = self._rank(both.ravel())

    def _rank(self, pairs: np.ndarray) -> np.ndarray:
        at = np.minimum(np.searchsorted(self.pairs, pairs), len(self.pairs) - 1)
        return np.where(self.pairs[at] == pairs, self.ranks[at], -1)

    def encode(self, words: list[bytes]) -> list[list[int]]:
        return list(map(unpacked, self.encode_packed(words)))

    def encode_packed(self, words: list[bytes]) -> list[bytes]:
        by_length: dict[int, list[int]] = {}
        for k, w in enumerate(words):
            by_length.setdefault((len(w) - 1).bit_length(), []).append(k)  # trees of one size
        out: list[bytes] = [b""] * len(words)
        for at in by_length.values():
            for lo in range(0, len(at), 10_000):  # bounds the trees' memory
                part = at[lo : lo + 10_000]
                lengths = np.array([len(words[k]) for k in part])
                n = int(lengths.max())
                raw = np.frombuffer(b"".join([words[k].ljust(n, b"\0") for k in part]), np.uint8).reshape(-1, n)
                rows = self._merge(raw, lengths) if n > 1 else self.byte_id[raw]
                stay = rows >= 0
                ids, hi = rows[stay].astype(np.int32).tobytes(), 0
                for k, end in zip(part, (4 * stay.sum(axis=1).cumsum()).tolist(), strict=True):
                    out[k] = ids[hi:end]
                    hi = end
        return out

    def _merge(self, raw: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        count, n = raw.shape
        size = 1 << (n - 1).bit_length()
        inside = np.arange(n) < lengths[:, None]
        symbols = np.where(inside, self.byte_id[raw], -1)
        first = np.where(inside[:, 1:], self.byte_pair_rank[raw[:, :-1].astype(np.int64) << 8 | raw[:, 1:]], -1)
        tree = np.full((count, 2 * size), _NONE, np.int64)
        tree[:, size : size + n - 1] = np.where(first >= 0, first * size + np.arange(n - 1), _NONE)
        level = size
        while level > 1:
            tree[:, level >> 1 : level] = np.minimum(tree[:, level : 2 * level : 2], tree[:, level + 1 : 2 * level : 2])
            level >>= 1
        nodes = tree.reshape(-1)
        after = np.tile(np.arange(1, n + 1), (count, 1))
        before = np.tile(np.arange(-1, n - 1), (count, 1))
        live = np.flatnonzero(tree[:, 1] != _NONE)
        while len(live):
            r, i = np.divmod(tree[live, 1], size)
            gone = after[live, i]
            symbols[live, i] = self.merged[r]
            symbols[live, gone] = -1
            nxt, p = after[live, gone], before[live, i]
            after[live, i] = nxt
            has_next, has_before = nxt < lengths[live], p >= 0
            before[live[has_next], nxt[has_next]] = i[has_next]
            own = symbols[live, i]
            right = self._rank(own << 20 | np.where(has_next, symbols[live, np.minimum(nxt, n - 1)], -1 & 0xFFFFF))
            left = self._rank(np.where(has_before, symbols[live, np.maximum(p, 0)], 0xFFFFF) << 20 | own)
            leaves = (
                (gone, np.full(len(live), _NONE)),
                (i, np.where(has_next & (right >= 0), right * size + i, _NONE)),
                (np.where(has_before, p, gone), np.where(has_before & (left >= 0), left * size + p, _NONE)),
            )
            root = live * (2 * size)
            for leaf, key in leaves:
                nodes[root + size + leaf] = key
            for leaf, _ in leaves:
                k = (size + leaf) >> 1
                while k[0]:  # the leaves of all rows are equally deep
                    at = root + k
                    below = at + k
                    nodes[at] = np.minimum(nodes.take(below), nodes.take(below + 1))
                    k = k >> 1
            live = live[tree[live, 1] != _NONE]
        return symbols


class ChunkEncoder:
    """Encodes whole texts; ``render`` turns the ids of a chunk into what is kept and joined for it.

    ``learn`` looks over some texts first and encodes all their new words together. The first ``entries`` chunks, which
    have most of the frequent ones, are kept; later ones are remembered for their own texts only.
    """

    def __init__(self, vocabulary: Vocabulary, render: Callable[[list[int]], object], entries: int = CACHE_ENTRIES):
        self.vocabulary, self.render, self.entries = vocabulary, render, entries
        self.batch = WordBatch(vocabulary)
        self.pattern = regex.compile(PRETOKEN)
        self.with_rare = regex.compile("(?V1)" + PRETOKEN.replace(r"\p{L}+", rf"[\p{{L}}--[{_RARE}]]+").replace(r"\p{N}+", rf"[\p{{N}}--[{_RARE}]]+").replace(r"[^\s\p{L}\p{N}]", rf"[[^\s\p{{L}}\p{{N}}][{_RARE}]]"))
        self.split_special = regex.compile("(" + "|".join(map(regex.escape, vocabulary.special)) + ")") if vocabulary.special else None
        self.simple = all(any(not (c.isalpha() or c in _ENDS) for c in special) for special in vocabulary.special)
        self.words: dict[str, bytes] = {}  # packed ids
        self.chunks: dict[str, object] = {"": None}
        self.passing: list[str] = []  # chunks of the last texts, beyond what is kept

    def _pretokens(self, text: str) -> list[str | int]:
        """Pre-tokens by the pattern; a special string stands as its id."""
        pieces = self.split_special.split(text) if self.split_special else [text]
        out: list[str | int] = []
        for piece in pieces:
            special = self.vocabulary.special.get(piece)
            if special is None:
                out += (self.with_rare if _HAS_RARE.search(piece) else self.pattern).findall(piece)
            else:
                out.append(special)
        return out

    def _chunk(self, chunk: str) -> list[str | int]:
        """Pre-tokens of a chunk and the blank before it; a plain word (and one mark behind it) needs no pattern."""
        if self.simple and (chunk.isascii() or max(chunk) < _SETTLED):
            if chunk.isalpha():
                return [" " + chunk]
            if chunk[-1] in _ENDS and chunk[:-1].isalpha():
                return [" " + chunk[:-1], chunk[-1]]
        return self._pretokens(" " + chunk)

    def _encode_new(self, words: set[str]) -> None:
        short = [w for w in words if w not in self.words and len(w) <= 32]
        self.words.update(zip(short, self.batch.encode_packed([w.encode() for w in short]), strict=True))

    def ids(self, text: str) -> list[int]:
        """Ids of any text, special strings becoming their own ids."""
        out: list[int] = []
        for word in self._pretokens(text):
            if isinstance(word, int):
                out.append(word)
            else:
                known = self.words.get(word)
                out += self.vocabulary.encode_word(word.encode()) if known is None else unpacked(known)
        return out

    def learn(self, texts: list[str]) -> None:
        for chunk in self.passing:
            self.chunks.pop(chunk, None)
        if len(self.words) > self.entries:
            self.words = {}
        seen: set[str] = set()
        for text in texts:
            seen.update(text.split(" "))
        fresh = [c for c in seen.difference(self.chunks) if len(c) <= 64]
        del seen
        for lo in range(0, len(fresh), 30_000):  # bounds what is held beside the ids
            self._learn_some(fresh[lo : lo + 30_000])
        self.passing = fresh if len(self.chunks) > self.entries else []

    def _learn_some(self, fresh: list[str]) -> None:
        pretokens = [self._chunk(c) for c in fresh]
        self._encode_new({w for words in pretokens for w in words if isinstance(w, str)})
        get = self.words.get
        for chunk, words in zip(fresh, pretokens, strict=True):
            if len(words) == 1 and (known := get(words[0])) is not None and chunk[0].isalpha():
                self.chunks[chunk] = known if self.render is packed else self.render(unpacked(known))
                continue
            if not chunk[0].isalpha() and _SPACE.match(chunk):
                self.chunks[chunk] = None
                continue
            ids: list[int] = []
            for w in words:
                if isinstance(w, int):
                    ids.append(w)
                else:
                    known = get(w)
                    ids += self.vocabulary.encode_word(w.encode()) if known is None else unpacked(known)
            self.chunks[chunk] = self.render(ids)

    def parts(self, text: str) -> list[object]:
        """Rendered chunks of the whole text, in order."""
        first, *rest = text.split(" ")
        out = list(map(self.chunks.get, rest))
        if None in out:
            for k, v in enumerate(out):
                if v is None:
                    if not rest[k] or _SPACE.match(rest[k]):
                        self._encode_new({w for w in self._pretokens(text) if isinstance(w, str)})
                        return [self.render(self.ids(text))]
                    out[k] = self.render(self.ids(" " + rest[k]))
        return [self.render(self.ids(first)), *out] if first else out


def some_at_a_time(texts: Iterable[str], most: int = 2_000_000) -> Iterator[list[str]]:
    """Runs of texts of about ``most`` characters, or of one longer text."""
    part: list[str] = []
    size = 0
    for text in texts:
        part.append(text)
        size += len(text)
        if size >= most:
            yield part
            part, size = [], 0
    if part:
        yield part


def _digest_batches(path: str, keep_ids: bool) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = Vocabulary(path)
        bytes_of = vocabulary.bytes_of
        shown = {i: b"%d" % i for i in bytes_of}
        encoder = ChunkEncoder(vocabulary, packed)  # a chunk's ids only: its digits and bytes come from the two maps
        for batch in batches:
            *others, texts = (batch.column(k) for k in range(batch.num_columns))
            row = 0
            for some in some_at_a_time(t for lo in range(0, len(texts), 250) for t in texts.slice(lo, 250).to_pylist()):
                encoder.learn(some)
                n_tokens, ids_sha, back_sha, kept = [], [], [], []
                for text in some:
                    joined = b"".join(encoder.parts(text))
                    ids = unpacked(joined)
                    n_tokens.append(len(ids))
                    ids_sha.append(hashlib.sha256(b",".join([shown[i] for i in ids])).hexdigest())
                    back = b"".join([bytes_of[i] for i in ids]).decode("utf-8", "replace")
                    back_sha.append(hashlib.sha256(back.encode()).hexdigest())
                    if keep_ids:
                        kept.append(np.frombuffer(joined, np.int32))
                made = [pa.array(n_tokens, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(back_sha, pa.string())]
                names = ["n_tokens", "ids_sha256", "decoded_sha256"]
                if keep_ids:
                    ends = np.cumsum([0, *map(len, kept)], dtype=np.int32)
                    made.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(kept))))
                    names.append("token_ids")
                yield pa.RecordBatch.from_arrays([*(c.slice(row, len(some)) for c in others), *made], [*batch.schema.names[:-1], *names])
                row += len(some)
            del batch, others, texts  # not held while the next batch is read

    return run


def encode_and_decode(df: DataFrame, tokenizer_path: str, text: str = "text", carry: tuple[str, ...] = ("doc_id",), keep_ids: bool = False) -> DataFrame:
    """Encode every whole text, decode its ids, and return both digests (and the ids, if asked for) beside ``carry``.

    One narrow pass: no shuffle, state bounded by ``CACHE_ENTRIES`` chunks a worker. Empty input gives no rows.
    """
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.select(*carry).schema)
    schema = f"{fields}, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", token_ids array<int>" * keep_ids
    return df.select(*carry, text_or_empty(text).alias("__text")).mapInArrow(tidy(_digest_batches(tokenizer_path, keep_ids)), schema)


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op10_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole ``documents``: token count, digest of the ids, digest of the decoded text."""
    return encode_and_decode(table(spark, sf_dir, "documents").select("doc_id", F.col("text")), default_tokenizer())
