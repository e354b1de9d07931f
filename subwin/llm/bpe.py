"""Byte-level BPE by prefix dynamic programming.

Of the tokens that end a prefix of a piece, exactly one can end the encoding of that prefix: the one
whose preceding prefix ends, by the same table, in a token that merges would leave beside it. Storing that
one token for each prefix makes appending exact and linear, and lets an edit reuse the table before it
and, once as many entries agree as a token is long, after it. Whether two tokens stay side by side is
told by undoing merges along the seam, latest first.

Defined results: a null text is empty; an empty one has no tokens, and both digests are of no bytes. Rows
with a null or repeated doc_id each get a row. Other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from itertools import chain

import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subwin.llm.common import map_batches, table, texts

#: Most entries of a worker's memos of words and of pairs.
MEMO, LONG = 400_000, 40
#: Unicode white space, and runs of two or more of it.
SPACES = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
RUNS = regex.compile(f"([{SPACES}]{{2,}})")
TOKEN = -1
#: Most bytes of a piece whose prefixes are worked out on demand, by recursion.
SHORT = 64


def read_ranks(path: str) -> dict[bytes, int]:
    """Token bytes and ranks of a file of base64 tokens and ranks."""
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


def merge_by_rank(ranks: dict[bytes, int], piece: bytes, leave: int = 1) -> list[bytes]:
    """The parts of a piece when adjacent parts of the least joint rank are merged, again and again, until ``leave`` are left."""
    parts = [piece[i : i + 1] for i in range(len(piece))]
    while len(parts) > leave:
        rank, at = min((ranks.get(parts[i] + parts[i + 1], 1 << 60), i) for i in range(len(parts) - 1))
        if rank == 1 << 60:
            break
        parts[at : at + 2] = [parts[at] + parts[at + 1]]
    return parts


class Vocabulary:
    """Ranks with what the dynamic program needs: each token's last merge, and the tokens that merges reach."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.size = 1 + max(ranks.values())
        self.bytes_of: list[bytes] = [b""] * self.size
        self.left, self.right = list(range(self.size)), list(range(self.size))
        self.reached: dict[bytes, int] = {}
        for token, rank in ranks.items():
            self.bytes_of[rank] = token
            parts = merge_by_rank(ranks, token, 2) if len(token) > 1 else [token]
            if len(parts) <= 2:
                self.reached[token] = rank
                self.left[rank], self.right[rank] = ranks[parts[0]], ranks[parts[-1]]
        self.longest = max(map(len, ranks))
        #: Tokens written backwards. Node: the byte before to its node, TOKEN to the token that is whole here.
        self.root: dict = {}
        for token, rank in self.reached.items():
            node = self.root
            for byte in reversed(token):
                node = node.setdefault(byte, {})
            node[TOKEN] = rank
        self._beside: dict[int, bool] = {}

    def beside(self, a: int, b: int) -> bool:
        """Whether merges leave tokens a and b side by side when they meet."""
        key = a << 32 | b
        known = self._beside.get(key)
        if known is None:
            if len(self._beside) >= MEMO:
                self._beside.clear()
            known = self._beside[key] = self._stay(a, b)
        return known

    def _stay(self, a: int, b: int) -> bool:
        bytes_of, ranks, left, right = self.bytes_of, self.ranks, self.left, self.right
        before = 1 << 60  # a merge over the seam at a rank below it would have come first
        while True:
            over = ranks.get(bytes_of[a] + bytes_of[b])
            if over is not None and over < before:
                return False
            # undo whichever of the two was merged later
            whole_a, whole_b = left[a] == a, left[b] == b
            if whole_a and whole_b:
                return True
            if whole_b or not whole_a and a > b:
                before, a = a, right[a]
            else:
                before, b = b + 1, left[b]

    def encode(self, piece: bytes) -> list[int]:
        whole = self.ranks.get(piece)
        if whole is not None:
            return [whole]
        last = [-1] * len(piece)
        # of a short piece only the prefixes that the whole one asks for are worked out
        for end in range(1 if len(piece) > SHORT else len(piece), len(piece) + 1):
            self.last_token(piece, last, end)
        return self.backwards(piece, last)

    def last_token(self, piece: bytes, last: list[int], end: int) -> int:
        """The one token that ends the encoding of piece[:end]; stored in last[end - 1], as are those of the prefixes asked for."""
        node, found = self.root, []
        for start in range(end - 1, -1, -1):
            node = node.get(piece[start])
            if node is None:
                break
            token = node.get(TOKEN)
            if token is not None:
                found.append((start, token))
        known = self._beside.get
        for start, token in reversed(found):
            if start:
                before = last[start - 1]
                if before < 0:
                    before = self.last_token(piece, last, start)
                fits = known(before << 32 | token)
                if not (self.beside(before, token) if fits is None else fits):
                    continue
            last[end - 1] = token
            return token
        raise ValueError("the vocabulary lacks a byte")

    def backwards(self, piece: bytes, last: list[int]) -> list[int]:
        """The whole encoding, read off the last tokens of prefixes."""
        out, end = [], len(piece)
        while end:
            out.append(token := last[end - 1])
            end -= len(self.bytes_of[token])
        return out[::-1]


class Prefixes:
    """A piece that grows and is edited, with the last token of the encoding of each of its prefixes."""

    def __init__(self, vocabulary: Vocabulary, piece: bytes = b""):
        self.vocabulary, self.piece, self.last = vocabulary, b"", []
        self.append(piece)

    def append(self, more: bytes) -> None:
        start = len(self.piece)
        self.piece += more
        self.last += [-1] * len(more)
        for end in range(start + 1, len(self.piece) + 1):
            self.vocabulary.last_token(self.piece, self.last, end)

    def edit(self, start: int, end: int, new: bytes) -> int:
        """Replace piece[start:end] by ``new``; returns how many entries were worked out anew."""
        old, shift = self.last, len(new) - (end - start)
        self.piece = self.piece[:start] + new + self.piece[end:]
        self.last = old[:start] + [-1] * (len(self.piece) - start)
        alike = 0
        for at in range(start, len(self.piece)):
            token = self.vocabulary.last_token(self.piece, self.last, at + 1)
            # an entry depends on as many entries before it as a token is long
            alike = alike + 1 if at >= start + len(new) and old[at - shift] == token else 0
            if alike == self.vocabulary.longest:
                self.last[at + 1 :] = old[at + 1 - shift :]
                return at + 1 - start
        return len(self.piece) - start

    def tokens(self) -> list[int]:
        return self.vocabulary.backwards(self.piece, self.last)


class Encoder:
    """Encodes and decodes whole texts; keeps a memo of up to MEMO words of less than LONG characters, for words recur.

    ``by_words``: the pattern never matches over the start of a single space between two words, so that words
    can be looked up whole. That holds for the public pattern; for others the default is to ask the pattern only.
    """

    def __init__(self, ranks: dict[bytes, int], pattern: str, by_words: bool = False):
        self.vocabulary, self.by_words = Vocabulary(ranks), by_words
        self.find = regex.compile(pattern).findall
        self._words: dict[str, tuple[int, ...]] = {}
        self._parts: dict[str, list[int]] = {}

    def _pieces(self, text: str) -> tuple[int, ...]:
        return tuple(chain.from_iterable(map(self._piece, self.find(text))))

    def _piece(self, piece: str) -> list[int]:
        known = self._parts.get(piece)
        if known is None:
            known = self.vocabulary.encode(piece.encode())
            if len(piece) < LONG:  # a long one hardly recurs
                if len(self._parts) >= MEMO:
                    self._parts.clear()
                self._parts[piece] = known
        return known

    def encode(self, text: str) -> array:
        """Ids of a text. By words, each word is looked up with the space before it; runs of white space go to the pattern."""
        ids = array("I")
        if not self.by_words:
            ids.extend(self._pieces(text))
            return ids
        parts = RUNS.split(text)
        for i, part in enumerate(parts):
            if i % 2:  # a run: its last character may belong to the word after it
                after = i + 1 < len(parts) and parts[i + 1] != ""
                ids.extend(self._pieces(part[:-1] if after else part))
                if after and part[-1] != " ":
                    ids.extend(self._pieces(part[-1]))
            elif part:
                words = part.split(" ")
                # a space before the first word: only where the run before it, or the text, ends in one
                if i and parts[i - 1][-1] == " ":
                    pass
                elif i == 0 and words[0] == "" and len(words) > 1:
                    words = words[1:]
                else:
                    ids.extend(self._pieces(words[0]))
                    words = words[1:]
                known = list(map(self._words.get, words))
                if None in known:
                    known = [k if k is not None else self._learn(w) for k, w in zip(known, words, strict=True)]
                ids.extend(chain.from_iterable(known))
        return ids

    def _learn(self, word: str) -> tuple[int, ...]:
        known = self._words.get(word)
        if known is None:
            if len(word) >= LONG:
                return self._pieces(" " + word)
            if len(self._words) >= MEMO:
                self._words.clear()
            known = self._words[word] = self._pieces(" " + word)
        return known

    def decode(self, ids) -> bytes:
        return b"".join(map(self.vocabulary.bytes_of.__getitem__, ids))


_ENCODERS: dict[str, Encoder] = {}


def encode_documents(docs: DataFrame, ranks: dict[bytes, int], pattern: str, with_ids: bool = False, by_words: bool | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of each document (doc_id, text); ``with_ids`` adds the ids.

    ``by_words`` (see Encoder) is true for the public pattern unless given. The vocabulary is broadcast: its size is that of the tokenizer, whatever the data's.
    """
    spark = docs.sparkSession
    by_words = pattern == public_pattern() if by_words is None else by_words
    name = hashlib.sha256(repr((sorted(ranks.items()), pattern, by_words)).encode()).hexdigest()
    sent = spark.sparkContext.broadcast(ranks)

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        encoder = _ENCODERS.get(name)
        if encoder is None:
            encoder = _ENCODERS[name] = Encoder(sent.value, pattern, by_words)
        counts, ids_sha, decoded_sha, lists = [], [], [], []
        for text in texts(batch):
            ids = encoder.encode(text)
            counts.append(len(ids))
            ids_sha.append(hashlib.sha256(ids.tobytes()).hexdigest())
            decoded_sha.append(hashlib.sha256(encoder.decode(ids)).hexdigest())
            if with_ids:
                lists.append(ids.tolist())
        arrays = [batch.column(0), pa.array(counts, pa.int64()), pa.array(ids_sha), pa.array(decoded_sha)]
        names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
        return pa.RecordBatch.from_arrays([*arrays, *([pa.array(lists, pa.list_(pa.int32()))] if with_ids else [])], names=[*names, *["ids"] * with_ids])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return map_batches(docs.select("doc_id", F.col("text")), run, f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids)


def decode_documents(encoded: DataFrame, ranks: dict[bytes, int]) -> DataFrame:
    """doc_id and text (bytes) of rows of doc_id, ids."""
    sent = encoded.sparkSession.sparkContext.broadcast({i: b for b, i in ranks.items()})

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        table = sent.value
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array([b"".join(map(table.__getitem__, ids or [])) for ids in batch.column(1).to_pylist()], pa.binary())], names=["doc_id", "text"])

    return map_batches(encoded.select("doc_id", "ids"), run, f"doc_id {encoded.schema['doc_id'].dataType.simpleString()}, text binary")


def public_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN


def public_vocabulary(name: str = "byte_bpe_multi_50k.tiktoken") -> tuple[dict[bytes, int], str]:
    import public_tokenizers

    return read_ranks(public_tokenizers.path(name)), public_pattern()


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(table(spark, sf_dir, "documents"), *public_vocabulary())
