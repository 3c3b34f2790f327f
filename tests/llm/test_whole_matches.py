"""Windows just over the similarity are found, whatever their shingles hash to."""

import random

import numpy as np

from graphdelta.llm import decontaminate


def test_windows_with_one_heavy_shingle_changed_are_found():
    lost = []
    for seed in range(200):
        rng = random.Random(seed)
        word = lambda n: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(n))  # noqa: B023, E731
        item = [word(4)] + [word(1) for _ in range(11)]
        changed = [word(4), *item[1:]]
        if not decontaminate.ItemIndex([(0, " ".join(item))]).search(" ".join(changed)):
            lost.append(seed)
    assert not lost


def test_searches_equal_all_windows():
    """Edited copies of items between other words: a loop over every window finds the same items, and as similar."""
    rng = random.Random(8)
    vocabulary = ["".join(rng.choice("abcdefghij") for _ in range(rng.randint(1, 9))) for _ in range(80)]
    items = [(i, " ".join(rng.choice(vocabulary) for _ in range(n))) for i, n in enumerate([1, 3, 5, 8, 12, 12, 20, 30, 30, 45, 60])]
    index = decontaminate.ItemIndex(items)
    similar = lost = 0
    for _ in range(400):
        i, text = rng.choice(items)
        words = text.split()
        n = len(words)
        for _ in range(rng.choice([0, 1, 1, 2, 3])):
            at = rng.randrange(len(words))
            words[at : at + rng.randrange(2)] = [rng.choice(vocabulary) * rng.choice([1, 1, 6])] * rng.randrange(2) or ["x"]
        words = [rng.choice(vocabulary) for _ in range(rng.randrange(12))] + words + [rng.choice(vocabulary) for _ in range(rng.randrange(12))]
        raw = decontaminate.words_of(" ".join(words))
        best = max(index.similar(raw[at : at + n], i) for at in range(max(1, len(raw) - n + 1)))
        got = {x[0]: x[3] for x in index.search(" ".join(words))}
        if best < decontaminate.SIMILARITY:
            assert i not in got
        else:
            similar += 1
            lost += abs(got.get(i, 0.0) - best) > 1e-9
    assert similar > 100 and lost <= 0.01 * similar


def test_a_window_that_neither_begins_nor_ends_at_a_shared_shingle_is_found():
    words = [f"word{k}" for k in range(30)]
    text = ["y" * 400, "a", *words[1:29], "b", "z" * 400]
    found = decontaminate.ItemIndex([(7, " ".join(words))]).search(" ".join(text))
    assert [(f[0], f[1], f[2]) for f in found] == [(7, 1, 30)]


def test_the_multi_index_finds_all_within_the_radius():
    rng = np.random.default_rng(4)
    prints = rng.integers(0, 1 << 16, (40, 8), dtype=np.uint16)
    asked = np.repeat(prints, 5, axis=0)
    for row in asked:
        for bit in rng.choice(128, rng.integers(20, 45), replace=False):
            row[bit // 16] ^= np.uint16(1 << (bit % 16))
    apart = np.bitwise_count(asked[:, None, :] ^ prints[None]).sum(axis=2)
    rows, places = decontaminate.MultiIndex(prints).within(asked)
    assert set(zip(rows.tolist(), places.tolist(), strict=True)) == set(zip(*[x.tolist() for x in np.nonzero(apart <= decontaminate.RADIUS)], strict=True))
