"""Token ids of whole texts, equal to the tokenizers library's, at several times its speed.

Byte-level vocabularies whose merges are ordered by id run through tiktoken
with ranks taken from the same file; word vocabularies part a text at white
space before any merge, so the ids of a text are those of its chunks in order,
and a worker keeps the ids of the chunks it has met in a table of bounded size.
Whole columns of texts are parted in numpy, each distinct chunk of a part is
looked up once, and chunks not met before go through tiktoken together, with a
byte for the end-of-word mark, if the vocabulary's merges allow it.
Texts that hold a special token's string go to the library.
"""

from __future__ import annotations

import json
import re
from array import array
from collections.abc import Iterator
from functools import cached_property, lru_cache
from itertools import pairwise
from pathlib import Path

import numpy as np
import pyarrow as pa
import regex

#: Unicode's White_Space characters.
WHITE = "\t\n\x0b\x0c\r \x85\xa0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000"
#: White space to Python's str.split(), not to Unicode.
SEPARATORS = re.compile("[\x1c-\x1f]")
SOLID = re.compile(f"[^{WHITE}]+")
#: Letters of ASCII and the Latin blocks up to U+024F; text of these, ASCII and nothing else needs no normal form.
LATIN = "A-Za-z\xc0-\xd6\xd8-\xf6\xf8-\u024f"
BEYOND_LATIN = re.compile(f"[^\x00-\x7f{LATIN}]")
#: Chunks of a text whose ids are given at once.
BLOCK = 4096
#: Entries of one generation of a worker's table, with the library's merge procedure and with another one.
HELD, HELD_BESIDE = 600_000, 300_000
#: Entries of one generation where whole columns are encoded; just under the size at which a dict doubles.
HELD_COLUMN = 690_000
#: Chunks longer than this are not held.
LONGEST = 64
#: Bytes of a column that are parted at once, up to the end of a chunk.
PART = 4 << 20
#: Stands for the end-of-word mark; texts with it go another way.
MARK = "\0"
IS_SPACE = np.isin(np.arange(256), [9, 10, 11, 12, 13, 32])


def byte_symbols() -> list[str]:
    """The printable stand-in of each byte in byte-level vocabularies: itself where printable, else from 256 upwards."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    return [chr(b) if b in plain else chr(256 + sum(x not in plain for x in range(b))) for b in range(256)]


SYMBOLS = byte_symbols()


def stand_in(piece: str) -> str:
    return piece if piece.isascii() and piece.isprintable() and " " not in piece else "".join([SYMBOLS[b] for b in piece.encode()])


class Held(dict):
    """key -> make(key), in two generations of bounded size: what is met again moves on, the rest goes."""

    def __init__(self, make, size: int):
        super().__init__()
        self.make, self.size = make, size
        self.old: dict[str, bytes] = {}

    def __missing__(self, key: str) -> bytes:
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        if len(key) <= LONGEST:
            self.make_room(1)
            self[key] = value
        return value

    def make_room(self, n: int) -> None:
        if len(self) + n > self.size:
            self.old = dict(self)
            self.clear()

    def several(self, keys: list, make_several) -> list[bytes]:
        """The values of distinct keys; those not held are made by one call of make_several."""
        values = list(map(self.get, keys))
        if absent := [k for k, v in enumerate(values) if v is None]:
            old = self.old.get
            for k in absent:
                values[k] = old(keys[k])
            new = [k for k in absent if values[k] is None]
            for k, v in zip(new, make_several([keys[k] for k in new]), strict=True):
                values[k] = v
            self.make_room(len(absent))
            short = [k for k in absent if len(keys[k]) <= LONGEST]
            self.update(zip([keys[k] for k in short], [values[k] for k in short], strict=True))
        return values


def ranked_by_id(model: dict) -> bool:
    """Whether merging by token id gives what merging by the merge list gives: every token of two symbols or more is made by a merge, in ascending order of ids."""
    vocab = model["vocab"]
    made = [vocab.get("".join(m if isinstance(m, list) else m.split(" ", 1)), -1) for m in model["merges"]]
    several = sum(len(t) > 1 for t in vocab)
    return all(a < b for a, b in zip([-1, *made], made, strict=False)) and len(made) == several


@lru_cache(maxsize=4)
def merges_by_name(path: str) -> bool:
    """Whether neighbours whose strings make a token may be merged in order of ids, whatever the merge list says, with the same ids as by the list.

    So it is if tokens of several symbols have one merge each, in ascending order
    of ids and after all symbols with an end-of-word mark, and if the list makes
    each token of its own symbols alone: two neighbours that make a token are then
    always the pair that its merge joins.
    """
    rules = json.loads(Path(path).read_text())
    model = rules["model"]
    mark = model.get("end_of_word_suffix")
    if not mark or any(model.get(k) for k in ("unk_token", "dropout", "continuing_subword_prefix", "ignore_merges", "byte_fallback")):
        return False
    vocab = {t: n for t, n in model["vocab"].items() if t not in {x["content"] for x in rules["added_tokens"]}}
    pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ", 1)) for m in model["merges"]]
    made, symbols = {a + b for a, b in pairs}, {*SYMBOLS, *(x + mark for x in SYMBOLS)}
    if not symbols <= vocab.keys() or len(made) != len(pairs) or made & symbols or made | symbols != vocab.keys():
        return False
    ascending = all(a < b for a, b in pairwise([max(vocab[x] for x in symbols), *(vocab[a + b] for a, b in pairs)]))
    if not ascending or any(a.endswith(mark) or (a + b).endswith(mark) != b.endswith(mark) for a, b in pairs):
        return False
    rank = {p: r for r, p in enumerate(pairs)}
    none = len(rank)
    for token in made:
        parts = [*token.removesuffix(mark)]
        parts[-1] += token[len(token.removesuffix(mark)) :]
        while len(parts) > 1:
            ranks = [rank.get(p, none) for p in pairwise(parts)]
            k = ranks.index(low := min(ranks))
            if low == none:
                return False
            parts[k : k + 2] = [parts[k] + parts[k + 1]]
    return True


class Encoder:
    """text -> its ids as little-endian unsigned 32-bit bytes, equal to encode(text, add_special_tokens=False).

    merge(piece) gives the ids of a piece between the vocabulary's own splits,
    in the vocabulary's stand-in characters; by default it is the library's model.
    The library itself is loaded only where it is needed.
    """

    def __init__(self, path: str, merge=None):
        self.path = path
        rules = json.loads(Path(path).read_text())
        self.special = {t["content"]: t["id"] for t in rules["added_tokens"]}
        self.ordinary = None
        self.bytewise = rules["pre_tokenizer"]["type"] == "ByteLevel"
        if self.bytewise:
            plain = {t: n for t, n in rules["model"]["vocab"].items() if t not in self.special}
            if ranked_by_id(rules["model"] | {"vocab": plain}):
                import tiktoken

                from public_tokenizers import PATTERN

                back = {c: b for b, c in enumerate(SYMBOLS)}
                ranks = {bytes(back[c] for c in token): n for token, n in plain.items()}
                self.ordinary = tiktoken.Encoding("ranks", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_to_numpy
        else:
            pattern = rules["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"]
            self.split = regex.compile(pattern).findall
            self.latin = re.compile(pattern.replace(r"\p{L}", LATIN).replace(r"\p{N}", "0-9"), re.ASCII).findall
            size = HELD_BESIDE if merge else HELD
            self.chunks, self.pieces = Held(self.solid, size), Held(self.piece, size)
            self.marked = False  # whether the text at hand holds a special token's string
            self.merge = merge or (lambda piece: [t.id for t in self.library.model.tokenize(piece)])

    @cached_property
    def library(self):
        from tokenizers import Tokenizer

        out = Tokenizer.from_file(self.path)
        out.no_truncation()
        out.no_padding()
        return out

    def __call__(self, text: str) -> bytes:
        if self.bytewise:
            if not self.ordinary or any(s in text for s in self.special):
                return array("I", self.library.encode(text, add_special_tokens=False).ids).tobytes()
            return self.ordinary(text).tobytes()
        return b"".join(self.stream(text))

    def stream(self, text: str) -> Iterator[bytes]:
        """The same in parts: of a word vocabulary BLOCK chunks at a time, otherwise whole."""
        if self.bytewise:
            yield self(text)
            return
        self.marked = any(s in text for s in self.special)
        chunks = SOLID.findall(text) if SEPARATORS.search(text) else text.split()
        for k in range(0, len(chunks), BLOCK):
            yield b"".join(map(self.chunks.__getitem__, chunks[k : k + BLOCK]))

    def solid(self, chunk: str) -> bytes:
        """Of text without white space."""
        if self.marked and any(s in chunk for s in self.special):
            parts = re.split(f"({'|'.join(map(re.escape, self.special))})", chunk)
            return b"".join(array("I", [self.special[x]]).tobytes() if k % 2 else self.solid(x) for k, x in enumerate(parts) if x)
        lower = chunk.lower()
        pieces = self.split(self.library.normalizer.normalize_str(chunk)) if BEYOND_LATIN.search(lower) else self.latin(lower)
        return b"".join(map(self.pieces.__getitem__, pieces))

    def piece(self, piece: str) -> bytes:
        return array("I", self.merge(stand_in(piece))).tobytes()

    def column(self, texts: pa.Array, by_name: bool = False) -> tuple[np.ndarray, np.ndarray]:
        """The ids of a column of texts, one text after the other, and how many are of each. by_name: what merges_by_name() says of the file."""
        if self.bytewise:
            raws = [self(text) for text in texts.to_pylist()]
            return np.frombuffer(b"".join(raws), "<u4"), np.array([len(raw) // 4 for raw in raws], np.int64)
        texts = texts.cast(pa.large_string())
        ends = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1] if len(texts) else np.zeros(1, np.int64)
        data, ends = np.frombuffer(texts.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]], ends[1:] - ends[0]
        last = np.zeros(len(data), bool)  # bytes that end a chunk or a text
        last[ends[ends > 0] - 1] = True
        made, total, held, at = [np.zeros(0, np.uint32)], np.zeros(len(ends), np.int64), 0, 0  # total: ids up to the end of each text
        while at < len(data):
            part = data[at : at + PART]
            space = IS_SPACE[part]
            cuts = np.flatnonzero(space | last[at : at + PART]) + 1
            if at + len(part) < len(data) and not len(cuts):  # a chunk longer than a part
                rest = IS_SPACE[data[at:]] | last[at:]
                part = data[at : at + int(rest.argmax()) + 1]
                space, cuts = IS_SPACE[part], np.array([len(part)])
            part, space = part[: cuts[-1]], space[: cuts[-1]]
            solid = cuts - np.cumsum(space)[cuts - 1]  # where each chunk ends among the bytes that are no white space
            ids, n = self.part(part[~space], solid, by_name)
            within = (ends > at) & (ends <= at + len(part))
            total[within] = held + np.cumsum(n)[np.searchsorted(cuts, ends[within] - at)]
            made.append(ids)
            held, at = held + len(ids), at + len(part)
        return np.concatenate(made), np.diff(total, prepend=0)

    def part(self, data: np.ndarray, ends: np.ndarray, by_name: bool) -> tuple[np.ndarray, np.ndarray]:
        """Ids of chunks that lie one after the other in data, and how many are of each."""
        chunks = pa.Array.from_buffers(pa.large_binary(), len(ends), [None, pa.py_buffer(np.concatenate([[0], ends])), pa.py_buffer(data)]).dictionary_encode()
        keys = chunks.dictionary.to_numpy(zero_copy_only=False).tolist()
        values = self.known.several(keys, self.named) if by_name else [self(key.decode()) for key in keys]
        sizes = np.fromiter(map(len, values), np.int64, len(values)) // 4
        code = chunks.indices.to_numpy()
        n = sizes[code]
        shift = (np.cumsum(sizes) - sizes)[code] - (np.cumsum(n) - n)
        return np.frombuffer(b"".join(values), "<u4")[np.arange(n.sum()) + np.repeat(shift, n)], n

    @cached_property
    def known(self) -> Held:
        return Held(None, HELD_COLUMN)

    @cached_property
    def by_name(self):
        """Text whose pieces all end with MARK -> ids."""
        import tiktoken

        rules = json.loads(Path(self.path).read_text())
        suffix = rules["model"]["end_of_word_suffix"]
        back = {c: b for b, c in enumerate(SYMBOLS)}
        mark, stand = MARK.encode(), SYMBOLS[MARK.encode()[0]]
        ranks = {mark: rules["model"]["vocab"][stand]}
        for token, n in rules["model"]["vocab"].items():
            if token not in self.special and stand not in token:
                ranks[bytes(back[c] for c in token.removesuffix(suffix)) + mark * token.endswith(suffix)] = n
        return tiktoken.Encoding("ranks", pat_str=f"[^{MARK}]*{MARK}", mergeable_ranks=ranks, special_tokens={}).encode_to_numpy

    @cached_property
    def lines(self):
        """Pieces of a Latin text of chunks in lower case, each line's end as one of its own."""
        return re.compile(self.latin.__self__.pattern + "|\n", re.ASCII).findall

    def needs_more(self, text: str) -> bool:
        return MARK in text or bool(SEPARATORS.search(text)) or any(s in text for s in self.special)

    def named(self, keys: list[bytes]) -> list[bytes]:
        """Of chunks without ASCII white space, together; those that need a normal form, another parting or special ids go alone."""
        text = b"\n".join(keys).decode()
        marked = self.needs_more(text)
        odd = [k for k, key in enumerate(keys) if len(key) > LONGEST or not key.isascii() and BEYOND_LATIN.search(key.decode().lower()) or marked and self.needs_more(key.decode())]
        if odd:
            gone = {*odd}
            text = b"\n".join([b"" if k in gone else key for k, key in enumerate(keys)]).decode()
        ids = self.by_name(MARK.join([*self.lines(text.lower()), "\n", ""])) if keys else np.zeros(0, np.uint32)
        line = ids == self.by_name("\n" + MARK)[0]
        ends = np.flatnonzero(line)
        raw, stops = ids[~line].astype("<u4").tobytes(), (4 * (ends - np.arange(len(ends)))).tolist()
        made = [raw[a:b] for a, b in pairwise([0, *stops])]
        for k in odd:
            made[k] = self(keys[k].decode())
        return made


_ENCODERS: dict[tuple, Encoder] = {}


def encoder(path: str, make_merge=None) -> Encoder:
    """One for each worker process, vocabulary file and merge procedure."""
    key = path, make_merge and make_merge.__name__
    if key not in _ENCODERS:
        _ENCODERS[key] = Encoder(path, make_merge and make_merge(path))
    return _ENCODERS[key]
