"""Byte-pair encoding and decoding by dynamic programming over prefixes.

For a fixed merge list the last token of the encoding of every prefix is unique. So one pass over a word suffices: an
automaton over the vocabulary lists, at each position, the tokens that end there; a token is the last one of the prefix
exactly if it may follow the last token of the prefix before it, that is, if encoding the two tokens' joint text gives the
pair back. Back-pointers then spell the ids. No priority queue, no repeated merging; cost is linear in the word.

Words repeat, so each Python worker keeps a bounded memo from white-space chunks to their ids and decoded text; the memo
changes speed only. Texts are streamed through ``mapInArrow``: no shuffle.

Edge cases: null and empty texts have no tokens (n_tokens 0, digests of the empty string); a word of any length is encoded
whole; rows are independent, so repeated rows, ties and extra columns don't matter.
"""

from __future__ import annotations

import hashlib
import json
import re
import unicodedata
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ._common import keep_memo_of, owns_memo

END = "\x00"  # stands for the end-of-word mark; byte symbols are printable, so it can't clash
MEMO = 400_000  # chunks a worker remembers
NEVER = 1 << 60  # rank of a pair that doesn't merge
_ODD_SPACE = re.compile("[\x1c-\x1f]")


def _byte_symbols() -> list[str]:
    """The printable stand-in of each byte: itself where printable, else the next free code point from 256 on."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    out, free = [], 256
    for b in range(256):
        if b in own:
            out.append(chr(b))
        else:
            out.append(chr(free))
            free += 1
    return out


class WordBpe:
    """Encoder and decoder for a tokenizer file of the `tokenizers` library with word-end marks."""

    def __init__(self, text: str):
        import ahocorasick
        import regex

        spec = json.loads(text)
        model = spec["model"]
        self.mark = model["end_of_word_suffix"]
        self.token_of = {i: t for t, i in model["vocab"].items()}
        self.token_of.update({t["id"]: t["content"] for t in spec["added_tokens"]})
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.split_added = regex.compile("(" + "|".join(map(regex.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        self.any_added = [a for a in self.added]
        pattern = next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.words = regex.compile(pattern).findall
        self.rank = {}
        for r, m in enumerate(model["merges"]):
            a, b = m if isinstance(m, list) else m.split(" ")
            self.rank.setdefault((self._inner(a), self._inner(b)), r)
        self.id_of = {self._inner(t): i for t, i in model["vocab"].items()}
        self.symbols = str.maketrans({chr(b): s for b, s in enumerate(_byte_symbols())})
        self.auto = ahocorasick.Automaton()
        for t, i in self.id_of.items():
            self.auto.add_word(t, (t, i, len(t)))
        self.auto.make_automaton()
        self.inner_of = {i: t for t, i in self.id_of.items()}
        self.pairs: dict[int, bool] = {}
        self.alone: dict[int, bool] = {}
        self.memo: dict[str, tuple[str, str]] = {}
        self.older: dict[str, tuple[str, str]] = {}
        self.word_memo: dict[str, tuple[str, str]] = {}

    def _inner(self, token: str) -> str:
        return token[: -len(self.mark)] + END if token.endswith(self.mark) else token

    def merged(self, s: str) -> list[str]:
        """The encoding by merging in rank order: what the pair test is defined by."""
        parts = list(s[:-2]) + [s[-2:]] if s.endswith(END) else list(s)
        rank = self.rank
        ranks = [rank.get(p, NEVER) for p in zip(parts, parts[1:], strict=False)]
        while ranks:
            best = min(ranks)
            if best == NEVER:
                break
            at = ranks.index(best)
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
            del ranks[at]
            if at < len(ranks):
                ranks[at] = rank.get((parts[at], parts[at + 1]), NEVER)
            if at:
                ranks[at - 1] = rank.get((parts[at - 1], parts[at]), NEVER)
        return parts

    def may_follow(self, before: int, tok: str, i: int) -> bool:
        """Whether a token may stand after another: the encoding of their joint text is the pair."""
        if len(self.pairs) > 500_000:
            self.pairs.clear()
        a = self.inner_of[before]
        ok = self.pairs[before << 20 | i] = self.merged(a + tok) == [a, tok]
        return ok

    def encode_word(self, word: str) -> list[int]:
        """word: byte symbols, not empty."""
        n = len(word)
        last = [-1] * (n + 2)  # of a prefix: its last token's id, and where that token starts
        begin = [0] * (n + 2)
        alone, pairs = self.alone, self.pairs
        for end, (tok, i, size) in self.auto.iter(word + END):
            p = end + 1
            if last[p] >= 0:
                continue
            start = p - size
            if start:
                before = last[start]
                if before < 0:
                    continue
                ok = pairs.get(before << 20 | i)
                if ok is None:
                    ok = self.may_follow(before, tok, i)
            else:
                ok = alone.get(i)
                if ok is None:
                    ok = alone[i] = len(self.merged(tok)) == 1
            if ok:
                last[p] = i
                begin[p] = start
        out, p = [], n + 1
        while p:
            out.append(last[p])
            p = begin[p]
        return out[::-1]

    def encode_plain(self, chunk: str) -> list[int]:
        """Ids of a text without added tokens in it."""
        return [i for w in self._split(chunk) for i in self.encode_word(self._symbols_of(w))]

    def _split(self, chunk: str) -> list[str]:
        if chunk.isascii():
            s = chunk.lower()
            return [s] if s.isalpha() else self.words(s)
        return self.words(unicodedata.normalize("NFC", chunk).replace("Σ", "σ").lower())

    def _symbols_of(self, word: str) -> str:
        if word.isascii() and word.isprintable():
            return word
        return word.encode().decode("latin-1").translate(self.symbols)

    def decode(self, ids: list[int]) -> str:
        return " ".join(self.token_of[i] for i in ids)

    def _strings(self, chunk: str) -> tuple[str, str]:
        got = self.memo.get(chunk)
        if got is None:
            got = self.older.get(chunk)
            if got is None:
                words = [self._word_strings(w) for w in self._split(chunk)]
                got = words[0] if len(words) == 1 else (" ".join([w[0] for w in words]), " ".join([w[1] for w in words]))
            if len(chunk) <= 64:
                if len(self.memo) >= MEMO // 2:
                    self.older, self.memo = self.memo, {}
                self.memo[chunk] = got
        return got

    def _word_strings(self, word: str) -> tuple[str, str]:
        got = self.word_memo.get(word)
        if got is None:
            ids = self.encode_word(self._symbols_of(word))
            got = (" ".join(map(str, ids)), self.decode(ids))
            if len(word) <= 64:
                if len(self.word_memo) >= MEMO // 4:
                    self.word_memo.clear()
                self.word_memo[word] = got
        return got

    def encode_strings(self, text: str) -> tuple[str, str]:
        """The ids in decimal, joined by a space, and the decoded text."""
        if any(a in text for a in self.any_added):
            ids: list[int] = []
            for part in self.split_added.split(text):
                ids += [self.added[part]] if part in self.added else self.encode_plain(part)
            return " ".join(map(str, ids)), self.decode(ids)
        chunks = text.split() if not _ODD_SPACE.search(text) else [text]
        memo = self.memo
        try:
            pairs = [memo[c] for c in chunks]
        except KeyError:
            one = self._strings
            pairs = [one(c) for c in chunks]
        if "" in (p[0] for p in pairs):
            pairs = [p for p in pairs if p[0]]
        return " ".join([p[0] for p in pairs]), " ".join([p[1] for p in pairs])

    def encode(self, text: str) -> list[int]:
        return [int(x) for x in self.encode_strings(text)[0].split()]


_LOADED: dict[int, WordBpe] = {}


def _codec(vocab) -> WordBpe:
    """One codec a worker process and vocabulary."""
    keep_memo_of("bpe")
    text = vocab.value
    key = hash(text)
    if key not in _LOADED:
        _LOADED.clear()
        _LOADED[key] = WordBpe(text)
    return _LOADED[key]


owns_memo("bpe", lambda: _LOADED.clear())


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def _broadcast(spark: SparkSession, path: str | None):
    with open(path or default_vocabulary(), encoding="utf-8") as f:
        return spark.sparkContext.broadcast(f.read())  # 1.7 MB; a vocabulary doesn't grow with the corpus


def encode_frame(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str | None = None) -> DataFrame:
    """(id, ids array<int>, decoded string) of each row."""
    vocab = _broadcast(docs.sparkSession, vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(vocab)
        for b in batches:
            ids, decoded = [], []
            for t in b.column(1):
                a, d = codec.encode_strings(t.as_py() or "")
                ids.append([int(x) for x in a.split()])
                decoded.append(d)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(ids, pa.list_(pa.int32())), pa.array(decoded, pa.string())], ["id", "ids", "decoded"])

    kind = docs.schema[id_col].dataType.simpleString()
    out = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(run, f"id {kind}, ids array<int>, decoded string")
    return out.withColumnRenamed("id", id_col)


def encode_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str | None = None) -> DataFrame:
    """(id, n_tokens, ids_sha256, decoded_sha256): what encode_frame gives, digested where it is made."""
    vocab = _broadcast(docs.sparkSession, vocabulary)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(vocab)
        for b in batches:
            n, x, y = [], [], []
            for t in b.column(1):
                a, d = codec.encode_strings(t.as_py() or "")
                n.append(a.count(" ") + 1 if a else 0)
                x.append(hashlib.sha256(a.encode()).hexdigest())
                y.append(hashlib.sha256(d.encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(x), pa.array(y)], ["id", "n_tokens", "ids_sha256", "decoded_sha256"])

    kind = docs.schema[id_col].dataType.simpleString()
    out = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInArrow(run, f"id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
    return out.withColumnRenamed("id", id_col)
