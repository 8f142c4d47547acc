"""Byte-level BPE as a monoid: halves are encoded apart and joined at their boundary.

An encoded text is a list of pieces (the matches of the split pattern) with the packed ids of each. Two of them
join as follows. The pattern (public_tokenizers.PATTERN; another one is not halved, as it may look further) looks at most
two characters past a match, so all pieces of the left half but those
that end within SLACK characters of its end are final. The characters of the rest, with some first pieces of the
right half, form a window that is split anew. A match depends only on the text after its start: as soon as a
stable match of the window starts where a piece of the right half starts, all that follow are the same, so those of
the right half stay. If there is no such start the window doubles, up to the whole right half.

A piece of more than PIECE_LEAF bytes is encoded in the same way on bytes. A token sequence is the BPE encoding of
its bytes if and only if that holds for each pair of neighbours, so a window of tokens around the cut is encoded
anew and grows until the pairs at its two ends are encodings themselves.

Decoding concatenates byte strings up the tree.

Null and empty texts have no tokens. Rows are independent: repeated rows give repeated results, other columns of
the input are left out, an empty table gives an empty table.
"""

from __future__ import annotations

import base64
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Characters of a leaf; longer texts are halved.
TEXT_LEAF = 1024
#: Bytes of a piece that is encoded without halving.
PIECE_LEAF = 8
#: Ids decoded at once.
DECODE_LEAF = 4096
#: The split pattern looks at less than so many characters behind the end of a match.
SLACK = 3
#: Distinct pieces remembered by a worker.
MEMO = 400_000
#: White space as the pattern's engine has it (the regex module's class also holds U+001C to U+001F).
SPACE = r"\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"

DEFAULT_VOCABULARY = "byte_bpe_50k.tiktoken"


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path(DEFAULT_VOCABULARY)


def default_pattern() -> str:
    import public_tokenizers

    return public_tokenizers.PATTERN


class Codec:
    """Encoder and decoder of one vocabulary."""

    def __init__(self, path: str, pattern: str):
        import regex
        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.bytes_of: list[bytes] = [b""] * (max(ranks.values()) + 1)
        for token, rank in ranks.items():
            self.bytes_of[rank] = token
        self._leaf = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})._core_bpe.encode_single_piece
        self.split = regex.compile(pattern.replace(r"(?!\S)", rf"(?![^{SPACE}])").replace(r"[^\s", rf"[^{SPACE}").replace(r"\s", f"[{SPACE}]")).findall
        self.text_leaf = TEXT_LEAF if pattern == default_pattern() else None
        self.memo: dict[str, bytes] = {}
        self.agree = lru_cache(200_000)(lambda a, b: self._leaf(self.bytes_of[a] + self.bytes_of[b]) == [a, b])

    # pieces

    def piece_ids(self, data: bytes) -> list[int]:
        if len(data) <= PIECE_LEAF:
            return self._leaf(data) if data else []
        half = len(data) // 2
        return self.join_ids(self.piece_ids(data[:half]), self.piece_ids(data[half:]))

    def join_ids(self, left: list[int], right: list[int]) -> list[int]:
        if not left or not right:
            return left or right
        if self.agree(left[-1], right[0]):
            return left + right
        i = j = 2
        while True:
            i, j = min(i, len(left)), min(j, len(right))
            window = self._leaf(b"".join(self.bytes_of[t] for t in left[len(left) - i :] + right[:j]))
            holds_left = i == len(left) or self.agree(left[-i - 1], window[0])
            holds_right = j == len(right) or self.agree(window[-1], right[j])
            if holds_left and holds_right:
                return left[: len(left) - i] + window + right[j:]
            i, j = i if holds_left else 2 * i, j if holds_right else 2 * j

    def packed(self, pieces: list[str]) -> list[bytes]:
        """The ids of each piece as little-endian 32-bit integers."""
        memo = self.memo
        try:
            return [memo[p] for p in pieces]
        except KeyError:
            pass
        for p in pieces:
            if p not in memo:
                memo[p] = np.array(self.piece_ids(p.encode()), "<u4").tobytes()
        out = [memo[p] for p in pieces]
        if len(memo) > MEMO:
            memo.clear()
        return out

    # texts

    def encoded(self, text: str) -> tuple[list[str], list[bytes]]:
        """Pieces and their packed ids."""
        if self.text_leaf is None or len(text) <= self.text_leaf:
            pieces = self.split(text)
            return pieces, self.packed(pieces)
        half = len(text) // 2
        return self.join(self.encoded(text[:half]), self.encoded(text[half:]))

    def join(self, left: tuple[list[str], list[bytes]], right: tuple[list[str], list[bytes]]) -> tuple[list[str], list[bytes]]:
        """The encoding of the concatenation; left is changed."""
        (pieces, ids), (more, more_ids) = left, right
        if not pieces or not more:
            return left if pieces else right
        behind, keep = 0, len(pieces)
        while keep and behind < SLACK:
            keep -= 1
            behind += len(pieces[keep])
        open_text, take = "".join(pieces[keep:]), 4
        while True:
            take = min(take, len(more))
            starts, at = {}, len(open_text)
            for k in range(take):
                starts[at] = k
                at += len(more[k])
            starts[at] = take
            again = self.split(open_text + "".join(more[:take]))
            end, stop = 0, None
            if take < len(more):
                for n, piece in enumerate(again):
                    if end in starts and n:
                        stop = n, starts[end]
                        break
                    end += len(piece)
                    if end > at - SLACK:
                        break
            else:
                stop = len(again), take
            if stop:
                break
            take *= 2
        del pieces[keep:], ids[keep:]
        pieces += again[: stop[0]]
        ids += self.packed(again[: stop[0]])
        pieces += more[stop[1] :]
        ids += more_ids[stop[1] :]
        return pieces, ids

    def encode(self, text: str) -> bytes:
        return b"".join(self.encoded(text)[1])

    def decode(self, ids: list[int]) -> bytes:
        if len(ids) <= DECODE_LEAF:
            return b"".join(map(self.bytes_of.__getitem__, ids))
        half = len(ids) // 2
        return self.decode(ids[:half]) + self.decode(ids[half:])


@lru_cache(2)
def codec(path: str, pattern: str) -> Codec:
    return Codec(path, pattern)


FIELDS = {"n_tokens": "long", "token_ids": "array<int>", "decoded": "binary", "text": "string", "ids_sha256": "string", "decoded_sha256": "string"}


def encode_texts(docs: DataFrame, outputs: list[str], keep: tuple[str, ...] = (), text_col: str = "text", path: str | None = None, pattern: str | None = None) -> DataFrame:
    """doc_id, the columns to keep and, of FIELDS, the outputs asked for: ids, the bytes they decode to, or digests of both."""
    import hashlib

    path, pattern = path or default_path(), pattern or default_pattern()

    def setup():
        tool = codec(path, pattern)

        def one(key, text, *others):
            packed = tool.encode(text)
            ids = np.frombuffer(packed, "<u4")
            out = {"n_tokens": len(ids)}
            if "token_ids" in outputs:
                out["token_ids"] = ids.astype("i4")
            if "ids_sha256" in outputs:
                out["ids_sha256"] = hashlib.sha256(packed).hexdigest()
            if {"decoded", "text", "decoded_sha256"} & set(outputs):
                out["decoded"] = tool.decode(ids.tolist())
                out["text"] = out["decoded"].decode()
                out["decoded_sha256"] = hashlib.sha256(out["decoded"]).hexdigest()
            return key, *others, *(out[k] for k in outputs)

        return one

    kept = "".join(f", `{k}` {docs.schema[k].dataType.simpleString()}" for k in keep)
    rows = docs.select("doc_id", common.text_of(text_col).alias("_text"), *keep)
    return common.map_rows(rows, setup, f"doc_id long{kept}, " + ", ".join(f"{k} {FIELDS[k]}" for k in outputs))


def op5_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document of the table encoded and decoded: token count and digests of ids and of the decoded bytes."""
    return encode_texts(common.documents(spark, sf_dir), ["n_tokens", "ids_sha256", "decoded_sha256"])


QUERIES = {"op5_byte_bpe": op5_byte_bpe}
ORACLES: dict[str, str] = {}
