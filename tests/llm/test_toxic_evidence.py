"""Evidence of toxicity: no veto by one text, no share of the sample, no cap on passages."""

import random

from kernmill.llm import toxicity

ORDINARY = [f"ordinary words about number{i} and weather in spring" for i in range(2000)]


def test_one_ordinary_text_vetoes_nothing():
    toxic = ["you are a grubblefink they said" for _ in range(90)] + ["another text of the kind"] * 210
    for quoted in (0, 1):
        runs = toxicity.toxic_runs(toxic, ORDINARY + ["somebody quoted grubblefink in class"] * quoted)
        assert " grub" in runs and runs["ubble"] == 90
    assert " grub" not in toxicity.toxic_runs(toxic, ORDINARY + ["somebody quoted grubblefink in class"] * 20)


def test_least_count_is_absolute():
    toxic = ["you are a grubblefink they said"] * 20 + [f"text{i} of the kind" for i in range(2480)]
    assert " grub" in toxicity.toxic_runs(toxic, ORDINARY * 4)


def test_every_passage_is_in_the_dictionary():
    rng = random.Random(4)
    slurs = ["".join(rng.choices("bcdfghjklmnpqrstvwxyz", k=12)) for _ in range(600)]
    toxic = [" ".join(slurs[i % 600 : i % 600 + 30]) for i in range(900)]
    made = toxicity.train_dictionaries(toxic, ORDINARY)
    assert all(w.encode() in made["toxic"] for w in slurs[15:])  # the first ones are in too few texts
