"""The ordinary dictionary sees whole texts, and only copies collapse."""

import random

from kernmill.llm import toxicity


def test_late_passages_reach_the_dictionary():
    rng = random.Random(5)
    noise = lambda n: " ".join("".join(rng.choices("abcdefghij", k=6)) for _ in range(n))
    late = "quietly observing riverbank herons every morning"
    texts = [f"{noise(120)} {late} {noise(40)}" for _ in range(300)]
    assert b"riverbank herons" in toxicity.train_dictionaries([], texts)["ordinary"]


def test_only_copies_collapse():
    rng = random.Random(6)
    words = [f"w{i}" for i in range(500)]
    apart = [" ".join(rng.choices(words, k=60)) + " extraordinarily" for _ in range(50)]
    edited = [t.replace(" extraordinarily", " plainly") for t in apart[:10]]
    assert toxicity._without_copies(apart) == apart
    assert toxicity._without_copies(apart + edited + apart) == apart
