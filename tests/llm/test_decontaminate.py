"""Windows against brute force, and the memory of a full shard."""

import random
import subprocess
import sys

import pytest

pytest.importorskip("hotgraph.llm")

from hotgraph.llm import decontaminate as d  # noqa: E402


def brute(text, items, width):
    words, hit, ids = d.normal_words(text), set(), set()
    for item, t in items:
        own = d.normal_words(t)
        n = min(width, len(own))
        for at in range(len(own) - n + 1 if own else 0):
            for k in range(len(words) - n + 1):
                if words[k : k + n] == own[at : at + n]:
                    hit |= set(range(k, k + n))
                    ids.add(item)
    return len(words), hit, ids


@pytest.mark.parametrize("width", [1, 2, 3, 5, 10])
def test_against_brute_force(width):
    r = random.Random(width)
    for _ in range(150):
        pool = [f"w{k}" for k in range(r.choice([2, 3, 30]))] + ["é1"]
        say = lambda n: " ".join(r.choice(pool) for _ in range(r.randrange(n)))
        items = [(r.randrange(4), say(25)) for _ in range(r.randrange(5))]
        known = d.Windows(items, width)
        for text in [*(say(40) for _ in range(4)), f"x {items[0][1].upper()}! y" if items else "", None]:
            n, found = known.scan(text)
            got = {k for a, b, _ in found for k in range(a, b)}
            assert (n, got, {i for *_, ids in found for i in ids}) == brute(text, items, width)


def test_a_full_shard_is_small():
    """New words only, the worst case: each costs a word of the vocabulary and nodes of its own."""
    code = (
        "import resource, random\nfrom hotgraph.llm import decontaminate as d\nr = random.Random(1)\n"
        "words = [format(r.getrandbits(28), 'x') for _ in range(d.SHARD_BYTES // 8)]\n"
        "items = [(k, ' '.join(words[k : k + 500])) for k in range(0, len(words), 500)]\n"
        "del words\nbefore = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss\nknown = d.Windows(items, 10)\n"
        "print((resource.getrusage(resource.RUSAGE_SELF).ru_maxrss - before) // 1024, known.scan(items[3][1])[0])\n"
    )
    out = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, check=True).stdout.split()
    assert int(out[0]) < 500 and out[1] == "500"
