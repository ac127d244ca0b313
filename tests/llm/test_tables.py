"""The encoder's tables of chunks: what they hold, and that special strings are found whatever was met before."""

from public_tokenizers import path
from tokenizers import Tokenizer

from tmotif.llm.tokens import Encoder

WORDS = str(path("word_bpe_49k.json"))


def test_half_a_million_chunks_are_encoded_once():
    encode = Encoder(WORDS)
    text = " ".join(map(str, range(550_000)))
    first = encode(text)
    made = []
    encode.chunks.make = lambda chunk: made.append(chunk) or encode.solid(chunk)
    assert encode(text) == first and not made


def test_special_strings_after_plain_texts():
    import numpy as np

    encode, library = Encoder(WORDS), Tokenizer.from_file(WORDS)
    special = [*encode.special]
    for text in ("plain words", f"plain {special[0]}words x{special[1]}", "plain words", special[0], f"a{special[0][:-1]} b"):
        assert np.frombuffer(encode(text), "<u4").tolist() == library.encode(text, add_special_tokens=False).ids


def test_columns_equal_the_library(monkeypatch):
    import numpy as np
    import pyarrow as pa

    from tmotif.llm import tokens

    library = Tokenizer.from_file(WORDS)
    special = [*Encoder(WORDS).special]
    texts = ["", "It's  the\tcat's\n\n'still' we'll '' ''s x'' 12 a1b2 --they're", " ", "a\x00b \x00 'S \x00's", "x\x1cy z\x1f", "non\xa0break wide \x85", f"a {special[0]}b{special[1]} {special[0][:-1]}", "Été été İstanbul ẞ ΣΣ 日本語 \U0001f600", "w" * 300 + " " + "ab" * 200 + ".", "", "Ā ĀĀ </w> a</w> Ġ", "the end of the end"]
    want = [library.encode(t, add_special_tokens=False).ids for t in texts]
    for part in (1, 7, tokens.PART):
        monkeypatch.setattr(tokens, "PART", part)
        for by_name in (True, False):
            ids, n = Encoder(WORDS).column(pa.array(texts * 2).slice(3, len(texts)), by_name)
            assert ids.tolist() == sum(want[3:] + want[:3], []) and n.tolist() == [len(x) for x in want[3:] + want[:3]]
    assert [len(x) for x in Encoder(WORDS).column(pa.array([], pa.string()), True)] == [0, 0]
    assert np.array_equal(Encoder(WORDS).column(pa.array(["", " \n"]), True)[1], [0, 0])


def test_new_words_of_a_column_go_together_and_once():
    import pyarrow as pa

    from tmotif.llm.tokens import merges_by_name

    assert merges_by_name(WORDS)
    encode, library = Encoder(WORDS), Tokenizer.from_file(WORDS)
    texts = [f"word{k}s qu{k % 50}xish, the {k}. Ünd" for k in range(2000)]
    encode.column(pa.array(texts), True)
    asked = []
    encode.by_name = (lambda f: lambda text: asked.append(text) or f(text))(encode.by_name)
    ids, _ = encode.column(pa.array(texts), True)
    assert ids.tolist() == [x for t in texts for x in library.encode(t, add_special_tokens=False).ids]
    assert not asked and "library" not in encode.__dict__  # the library's merges were not needed


def test_merges_that_names_do_not_tell(tmp_path):
    import json

    from tmotif.llm.tokens import SYMBOLS, merges_by_name

    def rules(merges, swap=False):
        vocab = {t: k for k, t in enumerate([*SYMBOLS, *(x + "</w>" for x in SYMBOLS), *("".join(m) for m in merges)])}
        if swap:
            a, b = "".join(merges[0]), "".join(merges[1])
            vocab[a], vocab[b] = vocab[b], vocab[a]
        (tmp_path / (name := f"{len(list(tmp_path.iterdir()))}.json")).write_text(json.dumps({"added_tokens": [], "model": {"vocab": vocab, "merges": merges, "end_of_word_suffix": "</w>"}}))
        return str(tmp_path / name)

    assert merges_by_name(rules([["a", "b"], ["ab", "c"], ["ab", "c</w>"]]))
    assert not merges_by_name(rules([["a", "b"], ["b", "c"], ["a", "bc"]]))  # of "abc" alone the list makes "ab", "c"
    assert not merges_by_name(rules([["a", "b"], ["ab", "c"]], swap=True))
    assert not merges_by_name(str(path("byte_bpe_50k.json")))


def test_blocks_of_every_width():
    import numpy as np

    from tmotif.llm import binary

    rng = np.random.default_rng(1)
    for width in range(33):
        for n in (1, 7, 8, 1023, 2500):
            ids = rng.integers(0, 2**width, n, dtype=np.uint64).astype(np.uint32)
            assert np.array_equal(binary.read_segment(binary.write_segment([1], [n], ids))[2], ids)
            bits = np.unpackbits(ids[:, None].astype("<u4").view(np.uint8), axis=1, bitorder="little")[:, :width]
            assert binary._packed(ids[None, :], width).tobytes() == np.packbits(bits.reshape(-1), bitorder="little").tobytes()
