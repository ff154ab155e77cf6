"""Byte-level BPE as a lazily determinised finite-state transducer.

The rank file is compiled into a byte trie of its tokens and a predicate: two tokens may follow
one another if byte-pair merging leaves their joint bytes as just these two. The encoding of
a piece is the one chain of tokens in which all neighbours may follow. The transducer reads bytes; its
state is the set of open tokens (a trie node, and the token before). A step that was taken before
is looked up; a new one is worked out once and kept. Each step tells the token that ends there;
tokens are emitted as soon as all open chains agree on them: lookahead is bounded by the longest token.
As the reference library does, a piece that is itself a token is that token.

Decoding streams: token bytes pass through an incremental UTF-8 state machine that holds back at most
three bytes of an unfinished character.

At scale: encoding is a narrow, vectorised projection over whole texts; the rank table (bounded by its
vocabulary) is read on the driver and broadcast; every memo has a bound.

Defined cases: null is empty; an empty text has no tokens; lone invalid bytes decode to U+FFFD; repeated rows
are encoded row by row; an empty table gives an empty table; extra columns are left unread or carried.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from itertools import chain

import pandas as pd
import public_tokenizers
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
#: The reference pattern, with its blanks spelled out as Unicode's White_Space.
WHITE = r"\t\n\x0b\x0c\r \x85\xa0  -     　"
#: Entries of the memos of pieces and of what may follow, and of states, which take most memory: beside a JVM that earlier stages have grown, two workers must fit one executor.
MEMO, STEPS = 600_000, 150_000
#: After so many times ``STEPS`` steps that were not kept all are forgotten: texts have changed.
PASSING = 10
ROOT, START, OPEN, NEVER = 0, -1, -1, 1 << 60
#: A piece longer than this many bytes is encoded as a stream.
LOOK = 256


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def plain_merge(piece: bytes, ranks: dict[bytes, int], below: int = NEVER) -> list[int]:
    """Byte-pair merging by the definition, with merges of a rank under ``below``: the least rank first, leftmost of equals."""
    parts = [piece[i : i + 1] for i in range(len(piece))]
    while len(parts) > 1:
        rank, i = min((ranks.get(a + b, NEVER), i) for i, (a, b) in enumerate(zip(parts, parts[1:], strict=False)))
        if rank >= below:
            break
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
    return [ranks[p] for p in parts]


class Transducer:
    """Over a rank table, bytes -> id; ids are the ranks of merges."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks, self.tokens = ranks, {i: b for b, i in ranks.items()}
        self.lengths = {i: len(b) for b, i in ranks.items()}
        self.child: dict[int, int] = {}
        self.token_at: dict[int, int] = {}
        self.inner: set[int] = set()
        self.halves: dict[int, tuple[int, int] | None] = {}
        self.follow: dict[int, bool] = {}
        self.depth = [0]
        for token, rank in ranks.items():
            at = ROOT
            for b in token:
                self.inner.add(at)
                key = at << 8 | b
                if key not in self.child:
                    self.child[key] = len(self.depth)
                    self.depth.append(self.depth[at] + 1)
                at = self.child[key]
            self.token_at[at] = rank
        self.reset()

    def reset(self) -> None:
        """Forget all states and what may follow. A state is a table byte -> (next state, token that ends there); under OPEN it has its open tokens."""
        self.start: dict = {OPEN: ((ROOT, START),)}
        self.known: dict[tuple, dict] = {self.start[OPEN]: self.start}
        self.n_steps = self.n_passing = 0
        self.follow.clear()

    def split(self, token: int) -> tuple[int, int] | None:
        """The two tokens that byte-pair merging joins last; None for a byte, or a token that merging never makes."""
        if token not in self.halves:
            parts = plain_merge(self.tokens[token], self.ranks, token)
            self.halves[token] = (parts[0], parts[1]) if len(parts) == 2 else None
        return self.halves[token]

    def may_follow(self, a: int, b: int) -> bool:
        """Does merging leave the bytes of a and b as a, b?

        Going back in time from the finished tokens, the parts that touch at the boundary are unmade in
        the reverse order of their making. If some two that touched had a merge that was due
        before either went into a larger part (on equal rank the left one merges first), it would have crossed.
        """
        key = a << 32 | b
        found = self.follow.get(key)
        if found is None:
            found = self._apart(a, b)
            if len(self.follow) < MEMO:
                self.follow[key] = found
        return found

    def _apart(self, a: int, b: int) -> bool:
        if self.lengths[b] > 1 and self.split(b) is None or a != START and self.lengths[a] > 1 and self.split(a) is None:
            return False
        if a == START:
            return True
        tokens, ranks = self.tokens, self.ranks
        a_goes = b_goes = NEVER
        while True:
            crossing = ranks.get(tokens[a] + tokens[b], NEVER)
            if crossing < a_goes and crossing <= b_goes and crossing != NEVER:
                return False
            left, right = self.split(a), self.split(b)
            if left is None and right is None:
                return True
            if right is None or left is not None and a > b:
                a_goes, a = a, left[1]
            else:
                b_goes, b = b, right[0]

    def step(self, state: dict, byte: int) -> tuple[dict, int]:
        """The state after ``byte``, and the token that ends the encoding of what has been read."""
        after, done, child, inner, token_at = [], None, self.child, self.inner, self.token_at
        for node, last in state[OPEN]:
            to = child.get(node << 8 | byte)
            if to is None:
                continue
            if done is None:
                token = token_at.get(to)
                if token is not None and self.may_follow(last, token):
                    done = token
            if to in inner:
                after.append((to, last))
        after.append((ROOT, done))
        new = tuple(after)
        at, room = self.known.get(new), self.n_steps < STEPS
        if at is None:
            at = {OPEN: new}
            if room:
                self.known[new] = at
        if room:
            self.n_steps += 1
            state[byte] = (at, done)
        else:
            # frequent states came first; what is worked out beyond them is not kept
            self.n_passing += 1
        return at, done

    def feed(self, pieces: Iterator[bytes]) -> Iterator[int]:
        """Tokens of a byte stream, each as soon as no open chain can undo it (checked every ``LOOK`` bytes)."""
        state, ends = self.start, []
        for chunk in pieces:
            for i in range(0, len(chunk), LOOK):
                for b in chunk[i : i + LOOK]:
                    state, token = state.get(b) or self.step(state, b)
                    ends.append(token)
                chains = [self.chain(ends, len(ends) - self.depth[node]) for node, _ in state[OPEN]]
                sure = 0
                while sure < min(map(len, chains)) and len({c[sure] for c in chains}) == 1:
                    sure += 1
                yield from chains[-1][:sure]
                del ends[: sum(self.lengths[t] for t in chains[-1][:sure])]
        yield from self.chain(ends, len(ends))

    def chain(self, ends: list[int], at: int) -> list[int]:
        """The tokens of the first ``at`` bytes, from the token that ends at each place."""
        out = []
        while at > 0:
            token = ends[at - 1]
            out.append(token)
            at -= self.lengths[token]
        out.reverse()
        return out

    def run(self, piece: bytes) -> tuple[int, ...]:
        whole = self.ranks.get(piece)
        if whole is not None:
            return (whole,)
        if self.n_passing > PASSING * STEPS:
            self.reset()
        if len(piece) > LOOK:
            return tuple(self.feed(iter((piece,))))
        state, ends = self.start, []
        put = ends.append
        for b in piece:
            found = state.get(b)
            if found is None:
                found = self.step(state, b)
            state, token = found
            put(token)
        return tuple(self.chain(ends, len(ends)))


class Utf8Stream:
    """Bytes in, whole characters out; what may still become a character is held back."""

    def __init__(self):
        self.held = b""

    @staticmethod
    def open_tail(data: bytes) -> int:
        """How many bytes at the end begin a character that is not complete."""
        for back in range(1, min(3, len(data)) + 1):
            b = data[-back]
            if b & 0xC0 == 0x80:
                continue
            need = 2 if 0xC2 <= b <= 0xDF else 3 if 0xE0 <= b <= 0xEF else 4 if 0xF0 <= b <= 0xF4 else 1
            return back if need > back else 0
        return 0

    def feed(self, data: bytes, last: bool = False) -> str:
        data = self.held + data
        cut = len(data) - (0 if last else self.open_tail(data))
        self.held = data[cut:]
        return data[:cut].decode("utf-8", "replace")


class Pieces(dict):
    """Piece -> its ids. When half of ``MEMO`` is new, what is older and was not asked for meanwhile goes, so frequent pieces stay."""

    def __init__(self, transducer: Transducer):
        super().__init__()
        self.transducer, self.older = transducer, {}

    def __missing__(self, piece: str) -> tuple[int, ...]:
        if len(self) > MEMO // 2:
            self.older = dict(self)
            self.clear()
        out = self.older.pop(piece, None)
        if out is None:
            out = self.transducer.run(piece.encode("utf-8"))
        if len(piece) <= LOOK:
            self[piece] = out
        return out


class ByteBpe:
    def __init__(self, ranks: dict[bytes, int], pattern: str = public_tokenizers.PATTERN):
        self.transducer = Transducer(ranks)
        self.pieces = Pieces(self.transducer)
        spelled = pattern.replace(r"[^\s", f"[^{WHITE}").replace(r"\S", f"[^{WHITE}]").replace(r"\s", f"[{WHITE}]")
        self.find = regex.compile(spelled).findall
        self.token_bytes = self.transducer.tokens
        self.digits = {i: str(i) for i in self.token_bytes}

    def encode(self, text: str) -> list[int]:
        return list(chain.from_iterable(map(self.pieces.__getitem__, self.find(text))))

    def digest(self, text: str) -> tuple[int, str, str]:
        """Number of ids, SHA-256 of the ids, SHA-256 of what they decode to."""
        ids = self.encode(text)
        decoded = hashlib.sha256()
        for part in self.decode_stream(ids):
            decoded.update(part.encode("utf-8"))
        return len(ids), hashlib.sha256(",".join(map(self.digits.__getitem__, ids)).encode()).hexdigest(), decoded.hexdigest()

    def decode_stream(self, ids: list[int], block: int = 4096) -> Iterator[str]:
        stream = Utf8Stream()
        for i in range(0, len(ids), block):
            yield stream.feed(b"".join(map(self.token_bytes.__getitem__, ids[i : i + block])))
        if stream.held:
            yield stream.feed(b"", last=True)

    def decode(self, ids: list[int]) -> str:
        return "".join(self.decode_stream(ids))


def ranks_of(path: str | None) -> dict[bytes, int]:
    return read_ranks(path or public_tokenizers.path(VOCABULARY))


def compiled(shared: dict) -> ByteBpe:
    """The coder of this worker process: a broadcast value outlives a task, so its memos do too."""
    if "coder" not in shared:
        shared["coder"] = ByteBpe(shared["ranks"])
    return shared["coder"]


def coder(spark: SparkSession, path: str | None, body, returns: str):
    """A vectorised function of a text column that runs ``body(bpe, text)``."""
    shared = spark.sparkContext.broadcast({"ranks": ranks_of(path)})

    @F.pandas_udf(returns)
    def code(texts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        bpe = compiled(shared.value)
        names = [x.split()[0] for x in returns.removeprefix("struct<").removesuffix(">").replace(":", " ").split(",")]
        for s in texts:
            yield pd.DataFrame([body(bpe, t or "") for t in s], columns=names)

    return code


def encode_digests(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", path: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of every row."""
    code = coder(docs.sparkSession, path, lambda bpe, t: bpe.digest(t), "struct<n_tokens:bigint,ids_sha256:string,decoded_sha256:string>")
    return docs.select(F.col(doc_id).alias("doc_id"), code(F.col(text)).alias("c")).select("doc_id", "c.*")


def encode(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", path: str | None = None) -> DataFrame:
    """doc_id, n_tokens and the token ids of every row."""
    code = coder(docs.sparkSession, path, lambda bpe, t: (len(ids := bpe.encode(t)), ids), "struct<n_tokens:bigint,ids:array<int>>")
    return docs.select(F.col(doc_id).alias("doc_id"), code(F.col(text)).alias("c")).select("doc_id", "c.*")


def decode(encoded: DataFrame, *, ids: str = "ids", to: str = "text", path: str | None = None) -> DataFrame:
    """``encoded`` and the text that its ids stand for."""
    shared = encoded.sparkSession.sparkContext.broadcast({"ranks": ranks_of(path)})

    @F.pandas_udf("string")
    def back(rows: Iterator[pd.Series]) -> Iterator[pd.Series]:
        bpe = compiled(shared.value)
        for s in rows:
            yield pd.Series([bpe.decode(list(x)) if x is not None else "" for x in s], dtype=object)

    return encoded.withColumn(to, back(F.col(ids)))
