"""Random strings without a digit, short ones, and ones glued to ordinary text are found."""

import random
import string

from parsieve.llm import secrets


def test_no_gate_before_the_model():
    model = secrets.train(secrets.labelled_samples())
    r = random.Random(8)
    found = lambda text: [text[a:b] for a, _, b in secrets.random_spans(text, model)]
    for n in (16, 19, 20, 32):
        letters = ["".join(r.choices(string.ascii_letters, k=n)) for _ in range(300)]
        mixed = ["".join(r.choices(string.ascii_letters + string.digits, k=n)) for _ in range(300)]
        assert sum(found(s) == [s] for s in letters + mixed) >= 0.99 * 600
        whole_or_part = lambda head, s: any(s in x for x in found(head + s))
        for head in ("some/long/path/to/another/module/", "ANOTHER_LONG_CONFIG_OPTION_NAME=", "list-of-default-values-"):
            assert sum(whole_or_part(head, s) for s in mixed) >= 0.98 * 300


def test_ordinary_strings_stay_unmarked():
    model = secrets.train(secrets.labelled_samples())
    ordinary = [s for s, y in secrets.labelled_samples(1000, "held-out") if not y]
    assert sum(bool(secrets.random_spans(s, model)) for s in ordinary) <= 0.01 * len(ordinary)
    for s in ("-" * 40, "=" * 40, "_" * 30, "-=" * 15, "Donaudampfschifffahrtsgesellschaft", "internationalization", "SOME_LONG_CONSTANT_NAME"):
        assert secrets.random_spans(s, model) == []
