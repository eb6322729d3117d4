"""Windows of conversations whose system turn is long; a word counts as one token."""


def windows(system, turns, budget=1024):
    from private_distinct.llm import chat

    held = chat.Windows(budget, 4, lambda s: len(s.split()))
    out = [w for role, n in [("system", system), *turns] for w in held.add(role, f"{role} " + "w " * n)]
    return [(w[2], w[3], w[4], [r for r, _ in chat.read_turns(w[5])]) for w in [*out, *held.rest()]]


def test_long_system_turn_is_retained():
    got = windows(600, [("user", 150), ("assistant", 100)] * 8)
    assert len(got) > 4 and sum(n for n, *_ in got) == 17
    assert all(roles.count("system") == 1 and roles[0] == "system" and tokens <= 1024 for _, _, tokens, roles in got)


def test_turn_that_does_not_fit_beside_it():
    got = windows(600, [("user", 100), ("assistant", 700), ("user", 100), ("assistant", 2000), ("user", 100)])
    assert sum(n for n, *_ in got) == 6
    for _, _, tokens, roles in got:
        assert tokens <= 1024 or tokens > 2000
    assert [("system" in roles) for *_, roles in got] == [True, False, True, True, True]
    assert [("system" in roles) for *_, roles in windows(600, [("user", 700), ("assistant", 100)])] == [True, False, True]


def test_system_turn_over_the_budget_is_an_ordinary_turn():
    got = windows(1500, [("user", 150), ("assistant", 100)] * 8)
    assert sum(n for n, *_ in got) == 17 and got[0][3] == ["system"]
    assert all("system" not in roles and tokens <= 1024 for _, _, tokens, roles in got[1:])
