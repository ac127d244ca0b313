"""BPE encoding by a bounded-lookahead transducer, and incremental decoding.

Whether a merge m = (u, v) happens depends on the text to its right only
through merges that take a token on the right edge of v away before it is used:
d = (t, w) of a lower rank than the merge that consumes t. reach(m), how far to
the right of m's end that chain goes, is therefore the largest |w| + reach(d)
over such d, computed in order of rank. The sufficient lookahead of the merge list is
the largest |w| + reach(d) of all merges: a token whose end has so many
symbols behind it in the window keeps its end whatever follows. Tokens are
emitted once stable and the window goes on from there, since the tokens to the
right of a boundary don't depend on what is left of it.
"""

from __future__ import annotations

import codecs
import hashlib
import heapq
import json
from bisect import bisect_left
from collections.abc import Iterable, Iterator
from functools import lru_cache
from itertools import islice
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame

from tmotif.llm.common import in_arrow, text_table
from tmotif.llm.tokens import SYMBOLS, encoder

#: Symbols that a window takes beyond the lookahead.
STRIDE = 256
#: Up to so many symbols a scan for the best pair is faster than a heap.
SHORT = 48


class Transducer:
    """The merge list of a vocabulary file: encode(piece) gives the ids of one piece in stand-in characters."""

    def __init__(self, path: str):
        model = json.loads(Path(path).read_text())["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.suffix: str = model.get("end_of_word_suffix") or ""
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ", 1)) for m in model["merges"]]
        self.rank = {p: r for r, p in enumerate(pairs)}
        self.lookahead = self._lookahead(pairs)

    def _symbols(self, token: str) -> int:
        return len(token.removesuffix(self.suffix) if self.suffix else token)

    def _lookahead(self, pairs: list[tuple[str, str]]) -> int:
        made: dict[str, list[tuple[str, int]]] = {}  # token -> (its right part, rank) of each merge that makes it
        for r, (a, b) in enumerate(pairs):
            made.setdefault(a + b, []).append((b, r))
        ranks: dict[str, list[int]] = {}  # token -> ranks of the merges that it begins
        most: dict[str, list[int]] = {}  # and the largest |w| + reach up to each
        best = 0
        for r, (a, b) in enumerate(pairs):
            reach, edge, seen = 0, [(b, r)], set()
            while edge:
                t, limit = edge.pop()
                if (t, limit) in seen:
                    continue
                seen.add((t, limit))
                if k := bisect_left(ranks.get(t, ()), limit):
                    reach = max(reach, most[t][k - 1])
                edge += [(right, q) for right, q in made.get(t, ()) if q < limit]
            far = self._symbols(b) + reach
            ranks.setdefault(a, []).append(r)
            most.setdefault(a, []).append(max(far, most[a][-1] if most.get(a) else 0))
            best = max(best, far)
        return best

    def _merged(self, parts: list[str]) -> list[str]:
        """Lowest rank first, of equal ranks the leftmost."""
        rank = self.rank
        if len(parts) <= SHORT:
            none = len(rank)
            pairs = [rank.get(p, none) for p in zip(parts, parts[1:], strict=False)]
            while pairs and (low := min(pairs)) < none:
                k = pairs.index(low)
                parts[k : k + 2] = [parts[k] + parts[k + 1]]
                del pairs[k]
                if k:
                    pairs[k - 1] = rank.get((parts[k - 1], parts[k]), none)
                if k < len(pairs):
                    pairs[k] = rank.get((parts[k], parts[k + 1]), none)
            return parts
        right, left = [*range(1, len(parts)), -1], [*range(-1, len(parts) - 1)]
        heap = [(r, k) for k in range(len(parts) - 1) if (r := rank.get((parts[k], parts[k + 1]))) is not None]
        heapq.heapify(heap)
        while heap:
            r, k = heapq.heappop(heap)
            j = right[k]
            if parts[k] is None or j < 0 or rank.get((parts[k], parts[j])) != r:
                continue
            parts[k] += parts[j]
            parts[j], right[k] = None, right[j]
            if right[j] >= 0:
                left[right[j]] = k
            for a, b in ((left[k], k), (k, right[k])):
                if a >= 0 and b >= 0 and (q := rank.get((parts[a], parts[b]))) is not None:
                    heapq.heappush(heap, (q, a))
        return [p for p in parts if p is not None]

    def stream(self, symbols: Iterable[str], stride: int = STRIDE) -> Iterator[str]:
        """Tokens of a piece given symbol by symbol, each as soon as it is stable; memory is lookahead + stride symbols."""
        symbols, window = iter(symbols), []
        while True:
            before, wanted = len(window), max(stride, self.lookahead + 1 + stride - len(window))  # one more symbol, since the last one of a piece bears its end mark
            window += islice(symbols, wanted)
            if len(window) < before + wanted:
                break
            at, stable = 0, len(window) - self.lookahead - 1
            for token in self._merged([*window]):
                if at + len(token) > stable:
                    break
                at += len(token)
                yield token
            del window[:at]
        if window:
            window[-1] += self.suffix
            yield from self._merged(window)

    def encode(self, piece: str) -> list[int]:
        return [self.vocab[t] for t in self.stream(piece)]


class Decoder:
    """The bytes of each token of a vocabulary file. With a byte-level decoder tokens follow each other, with none they are joined by a blank."""

    def __init__(self, path: str):
        rules = json.loads(Path(path).read_text())
        bytewise = (rules.get("decoder") or {}).get("type") == "ByteLevel"
        self.between = b"" if bytewise else b" "
        tokens = {n: t for t, n in rules["model"]["vocab"].items()} | {t["id"]: t["content"] for t in rules["added_tokens"]}
        back = {c: bytes([b]) for b, c in enumerate(SYMBOLS)}
        special = {t["id"] for t in rules["added_tokens"]}
        self.token = {n: t.encode() if n in special or not bytewise else b"".join(back[c] for c in t) for n, t in tokens.items()}

    def stream(self, ids: Iterable[int]) -> Iterator[str]:
        state = DecoderState(self)
        for n in ids:
            if text := state.feed([n]):
                yield text
        if text := state.end():
            yield text


class DecoderState:
    """What is known between two calls of a decoding: whether a token came, and the bytes of a character that isn't whole."""

    def __init__(self, decoder: Decoder):
        self.decoder, self.first = decoder, True
        self.utf8 = codecs.getincrementaldecoder("utf-8")("replace")

    def feed(self, ids: list[int]) -> str:
        """The text that these ids complete."""
        raw = self.decoder.between.join(map(self.decoder.token.__getitem__, ids))
        if ids and not self.first:
            raw = self.decoder.between + raw
        self.first &= not ids
        return self.utf8.decode(raw)

    def end(self) -> str:
        return self.utf8.decode(b"", True)


@lru_cache(maxsize=4)
def transducer(path: str) -> Transducer:
    return Transducer(path)


@lru_cache(maxsize=4)
def decoder(path: str) -> Decoder:
    return Decoder(path)


def merge_procedure(path: str):
    return transducer(path).encode


def _coded(path: str, with_text: bool):
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, decode = encoder(path, merge_procedure), decoder(path)
        for batch in batches:
            n, ids_sha, text_sha, ids, texts = [], [], [], [], []
            for text in batch.column(1).to_pylist():
                total, of_ids, of_text, back = 0, hashlib.sha256(), hashlib.sha256(), DecoderState(decode)
                kept: tuple[list[int], list[str]] = ([], [])
                for raw in encode.stream(text):
                    some = memoryview(raw).cast("I").tolist()
                    total += len(some)
                    of_ids.update(raw)
                    said = back.feed(some)
                    of_text.update(said.encode())
                    if with_text:
                        kept[0].extend(some)
                        kept[1].append(said)
                said = back.end()
                of_text.update(said.encode())
                n.append(total)
                ids_sha.append(of_ids.hexdigest())
                text_sha.append(of_text.hexdigest())
                if with_text:
                    ids.append(kept[0])
                    texts.append("".join([*kept[1], said]))
            cols, names = [batch.column(0), pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if with_text:
                cols, names = [*cols, pa.array(ids, pa.list_(pa.int64())), pa.array(texts, pa.string())], [*names, "ids", "decoded"]
            yield pa.RecordBatch.from_arrays(cols, names)

    return make


def bpe_round_trip(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """One row per input row: doc_id, n_tokens, ids_sha256, decoded_sha256 (and ids, decoded, if asked for).

    For word vocabularies (white space dropped, end-of-word suffix). Null and empty texts have no ids and decode to the
    empty text. Rows are independent: null ids and repeated rows stay as they are, each with its own result; other columns are not looked at.
    Ids leave the encoder a block of chunks at a time and go through the decoder's state, so that beside the text only such a block is held.
    """
    return in_arrow(text_table(docs, id_col, text_col), _coded(tokenizer, with_text), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<long>, decoded string" * with_text)
