"""Ids of remembered pre-tokens against the library's ids of whole texts."""

import random

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from routefront.llm import packing

PATH = public_tokenizers.path("byte_bpe_50k.json")


def test_ids_of_any_text_are_the_library_s():
    plain = Tokenizer.from_file(PATH)
    plain.encode_special_tokens = True
    r = random.Random(5)
    parts = [" ", "\n", "a", "Wor", "éa", "ñ", "'", "'s", "'ll", "12", ".", "...", "¿", "»", "²", "ª", "я", "\0", "\x1c", "­", "ɐ", "ǆ", "\t", "　", "😀", "<|endoftext|>", "don't", " they're,", "_", "x" * 300]
    texts = ["", *("".join(r.choices(parts, k=r.randint(1, 12))) for _ in range(1500)), *(" ".join(r.choices(parts[2:12] + parts[-4:], k=9)) for _ in range(1500))]
    got = packing._packer(PATH).encode_all(texts)
    assert [np.frombuffer(x, "<u4").tolist() for x in got] == [plain.encode(t, add_special_tokens=False).ids for t in texts]


def test_a_word_is_encoded_once_whatever_mark_follows_it():
    packing._packers.clear()
    enc = packing._packer(PATH)
    made, units = [], enc.units
    enc.units = lambda parts: made.extend(parts) or units(parts)
    enc.encode_all(["the thorlynd, the thorlynd. the thorlynd!", "or thorlynd?\nSo thorlynd"])
    enc.encode_all(["a thorlynd; or thorlynd"])
    assert made.count(" thorlynd") == 1 and len(made) == len(set(made))
    packing._packers.clear()
