import random

import numpy as np

from graphdrift.llm import transcripts as m


def rows(n, seed=3):
    random.seed(seed)
    out = []
    for c in range(n):
        role = "user"
        if c % 5 == 0:
            out.append((c, 0, "system", "Be brief. " * 3))
        for t in range(1, random.randint(2, 9)):
            text = " ".join("abc def?" for _ in range(random.randint(1, 4))) if role == "user" else "\n".join("x" * random.randint(100, 500) for _ in range(random.randint(1, 6)))
            out.append((c, t, role, text))
            role = "assistant" if role == "user" else "user"
    return out


def best_by_brute_force(model, symbols):
    import itertools

    def score(path):
        total, last = 0, m.START
        for s, x in zip(path, symbols):
            total += model.moves[last, s] + model.shown[s, x]
            last = s
        return total

    return max(itertools.product(range(m.STATES), repeat=len(symbols)), key=score)


def test_viterbi_equals_enumeration():
    rng = np.random.default_rng(0)
    model = m.Hmm(rng.integers(0, 50, (7, 6)).astype(float), rng.integers(0, 50, (6, m.SYMBOLS)).astype(float))
    for _ in range(5):
        symbols = rng.integers(0, m.SYMBOLS, 5).tolist()
        want = list(best_by_brute_force(model, symbols))
        assert model.path(symbols, m.START) == want
        # the same in two blocks
        a, b = model.matrix(symbols[:2]), model.matrix(symbols[2:])
        through = a[m.START][:, None] + b[:6]
        i, j = np.unravel_index(through.argmax(), through.shape)
        assert model.path(symbols[:2], m.START, i) + model.path(symbols[2:], i, j) == want


def test_markers():
    for style in m.STYLES:
        for k, role in enumerate(m.ROLES):
            line = style.format(role=role, Role=role.capitalize()).rstrip("\n").split("\n")[0] + "hello"
            if "\n" not in style:
                assert m.marker_of(line) == (k, "hello")
    assert m.marker_of("### User")[0] == 1 and m.marker_of("plain text")[0] == 3 and m.marker_of("a dog")[0] == 3


def test_roles_recovered_and_blocks_agree(spark, monkeypatch):
    data = rows(60) + [(None, None, None, None), (500, 1, "user", "x"), (500, 1, "user", "x")]
    conv = spark.createDataFrame(data, "conv_id long, turn long, role string, text string")
    raw = m.raw_conversations(conv)
    made = {(r.conv_id, r.turn): r.raw for r in raw.collect()}
    assert all(made[c, t] == m.raw_turn(c, t, r, x) for c, t, r, x in data)
    ordered = m.ordered_turns(raw)
    model = m.train(ordered)
    got = {(r.conv_id, r.turn): r for r in m.parse_turns(ordered, model).collect()}
    right = sum(got[c, t].roles[0] == r for c, t, r, _ in data if r)
    assert right / len(data) > 0.95
    for c in range(60):  # one path through a whole conversation, whatever the blocks
        turns = sorted(t for k, t, _, _ in data if k == c)
        lines = [x for t in turns for x in made[c, t].split("\n")]
        states = model.path([m.symbol_of(x) for x in lines], m.START)
        assert [r for t in turns for r in got[c, t].roles] == [m.ROLES[s // 2] for s in states]
        text = "\n".join(x for t in turns for x in got[c, t].rendered)
        assert text.startswith("<|") and text.count("<|end|>") == text.count("|>\n") - text.count("<|end|>\n") - 1
    out = m.recovered_roles(conv)
    assert out.count() == len(data) and m.recovered_roles(conv.limit(0)).count() == 0
