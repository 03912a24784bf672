"""The encoder's pieces by number: same ids as the library's, and few pieces kept."""

import numpy as np

from derivatrace.llm import registry, token_output


def test_ids_are_the_librarys_while_pieces_are_forgotten():
    enc = token_output.Encoder(registry.TOKENIZER, most=40)
    plain = enc.tokenizer
    rng = np.random.default_rng(5)
    met = []
    for k in range(12):
        words = ["".join(map(chr, rng.integers(97, 123, 6))) for _ in range(60)]
        texts = ["the cat and " + " ".join(words[:30]), "A line\nthe cat " + " ".join(words[30:]), "it's  odd,\tisn't it? " + words[0], "", "é Ωmega the 龥 <|endoftext|>", "​unsure the"]
        got = enc.encode(texts)
        assert [np.frombuffer(x, enc.kind).tolist() for x in got] == [plain.encode(t, add_special_tokens=False).ids for t in texts]
        met.append(len(enc.lengths))
    assert max(met) <= 2 * 40 + 100 and min(met[1:]) < max(met)
    # Frequent pieces stay known, under one row of numbers.
    assert "cat" in enc.spaced and sorted([*enc.known.values(), *enc.spaced.values()]) == list(range(len(enc.lengths)))
