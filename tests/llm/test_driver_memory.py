"""What the driver holds while it learns."""

import random
import tracemalloc

from kinetrace.llm import langid


def test_language_fit_holds_one_round_at_a_time(monkeypatch):
    """The arrays of a round are gone before the next, and the features of the texts aren't made anew in it."""
    rng, made, plain = random.Random(2), [], langid.features
    letters = ["abcdefgh", "ghijklmn"]
    texts = [" ".join("".join(rng.choices(letters[i % 2], k=6)) for _ in range(1000)) for i in range(40)]
    langs = [("x", "y")[i % 2] for i in range(40)]
    langid.fit(texts, langs, rounds=1)  # what modules keep
    monkeypatch.setattr(langid, "features", lambda w: (made.append(1), plain(w))[1])
    tracemalloc.start()
    langid.fit(texts, langs, rounds=3)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert len(made) == 1
    assert peak < 800 * 40_000  # bytes a word
