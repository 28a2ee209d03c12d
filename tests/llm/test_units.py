"""Ids of single units by merges alone."""

import numpy as np

from frontfill.llm.units import WORD_UNITS, plain, tokenizer, unit_ids


def test_unit_ids_are_the_library_s():
    tok = tokenizer("word_bpe_49k.json")
    ids = unit_ids(tok)
    marks = "".join(chr(i) for i in [*range(33, 127), *range(0xA1, 0xAD), *range(0xAE, 0x130), *range(0x132, 0x138), *range(0x139, 0x149), *range(0x14A, 0x17F)])
    text = "It's naïve: they'll pay 1234½ €5 ... œuvre ÀÉÎ straße — “so” ªº µ!? " + " ".join(marks) + " " + marks
    assert plain(text.replace("€", ""))
    for u in WORD_UNITS.findall(text.lower()):
        assert ids(u) == np.array(tok.encode(u, add_special_tokens=False).ids, np.uint32).tobytes(), u
