"""Adjacent words as features of the quality classifier."""

import numpy as np

from llm import quality


def pairs(text):
    f, _ = quality.features([text])
    return set(f[f >= 2 << quality.BITS].tolist())


def test_a_word_said_twice_is_one_feature():
    assert len(pairs("ber ber ber")) == 1 and pairs("ber ber ber") == pairs("menteos menteos")
    assert pairs("ber menteos") != pairs("ber ber") and not pairs("ber") and not pairs("")


def test_pairs_end_with_their_text():
    together, at = quality.features(["ab cd", "cd ab"])
    alone = [quality.features([t])[0] for t in ("ab cd", "cd ab")]
    assert all((together[a:b] == f).all() for a, b, f in zip(at[:-1], at[1:], alone, strict=True))


def test_repetition_of_unseen_words_is_learned():
    rng = np.random.default_rng(5)
    words = ["".join(rng.choice(list("abcdefghij"), 6)) for _ in range(900)]
    good = [" ".join(rng.choice(words[:300], 40)) for _ in range(60)]
    bad = [" ".join(w for w in rng.choice(words[:300], 5) for _ in range(8)) for _ in range(60)]
    model = quality.train(good + bad, [1] * 60 + [0] * 60)
    fresh = model.score([" ".join(rng.choice(words[600:], 40)), " ".join(w for w in rng.choice(words[600:], 5) for _ in range(8))])
    assert fresh[0] > 0.5 > fresh[1]
