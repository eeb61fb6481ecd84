"""Pre-tokens that share a rank queue get the ids that each gets alone."""

import random

from fdrepair.llm import bpe


def plain(ranks, piece):
    """The leftmost pair of the least rank is merged until there is none."""
    if piece in ranks:
        return [ranks[piece]]
    parts = [piece[i : i + 1] for i in range(len(piece))]
    while found := min(((ranks[a + b], i) for i, (a, b) in enumerate(zip(parts, parts[1:])) if a + b in ranks), default=None):
        parts[found[1] : found[1] + 2] = [b"".join(parts[found[1] : found[1] + 2])]
    return [ranks[x] for x in parts]


def test_pretokens_share_a_queue():
    for seed in range(60):
        draw = random.Random(seed)
        tokens = {b"a", b"b", b"c"} | {bytes(draw.choices(b"abc", k=draw.randint(2, 5))) for _ in range(40)}
        ranks = {x: k for k, x in enumerate(draw.sample(sorted(tokens), len(tokens)))}  # merges may give pairs of a lower rank
        pieces = [bytes(draw.choices(b"abc", k=draw.randint(1, 30))) for _ in range(40)]
        assert bpe.ByteBPE(ranks, r"\S+").all_ids(pieces) == [plain(ranks, x) for x in pieces]


def test_new_words_are_queued_together_and_old_ones_stay(monkeypatch):
    ranks = {bytes([c]): c for c in range(256)} | {b"ab": 256, b"abc": 257}
    coder, calls = bpe.ByteBPE(ranks, r"\S+"), []
    monkeypatch.setattr(bpe, "CACHED_WORDS", 80)
    of = coder.all_ids
    coder.all_ids = lambda x: calls.append(len(x)) or of(x)
    texts = [f"abcab w{k} w{k + 1} abca" for k in range(30)] + [None, "", "x" * 100]
    got = list(coder.encode_all(texts))
    assert calls == [33, 1] and got == [[i for w in (t or "").split() for i in plain(ranks, w.encode())] for t in texts]
    list(coder.encode_all([f"v{k}" for k in range(20)]))  # the older half is dropped only after another half
    assert coder["abcab"] == (257, 256) and calls == [33, 1, 20]


def test_a_worker_forgets_and_encodes_again():
    ranks = {bytes([c]): c for c in range(256)} | {b"ab": 256}
    coder = bpe.ByteBPE(ranks, r"\S+")
    first = list(coder.encode_all(["ab abc"]))
    coder.forget()
    assert not coder and not coder.older and list(coder.encode_all(["ab abc"])) == first == [[256, 256, 99]]
