import random

import pytest

from patternwalk.operators.queue import PatternQueue, QueuePolicy, iterate


class Plain:
    """The queue as a list that is sorted whenever asked."""

    def __init__(self, policy):
        self.policy, self.entries = policy, {}

    def order(self):
        return sorted(self.entries, key=lambda c: (-len(self.entries[c][0]), -self.entries[c][1], -self.entries[c][2], c))

    def passes(self, score):
        if self.policy.gate == "off" or len(self.entries) < self.policy.capacity:
            return True
        o = self.order()
        tail = o[len(o) - max(1, len(o) // 2) :]
        mean = sum(self.entries[c][1] for c in tail) / len(tail)
        return score >= mean if self.policy.ties == "admit" else score > mean

    def offer(self, code, gid, score, time):
        if self.policy.gate == "before_lookup" and not self.passes(score):
            return
        if code in self.entries:
            if gid not in self.entries[code][0]:
                self.entries[code][0].add(gid)
                self.entries[code][2] = time
            return
        if self.policy.gate == "after_lookup" and not self.passes(score):
            return
        if len(self.entries) >= self.policy.capacity:
            del self.entries[self.order()[-1]]
        self.entries[code] = [{gid}, score, time]


@pytest.mark.parametrize("gate", ["before_lookup", "after_lookup", "off"])
@pytest.mark.parametrize("ties", ["admit", "reject"])
@pytest.mark.parametrize("capacity", [1, 4, 7])
def test_against_a_sorted_list(gate, ties, capacity):
    rng = random.Random(capacity)
    policy = QueuePolicy(capacity, gate, ties)
    score = {f"c{i}": float(rng.randrange(1, 9)) for i in range(30)}
    rows = [((c := rng.choice(list(score))), rng.randrange(6), score[c], t) for t in range(600)]
    plain = Plain(policy)
    for r in rows:
        plain.offer(*r)
    queue = iterate(rows, policy)
    assert [(c, sorted(plain.entries[c][0]), *plain.entries[c][1:]) for c in plain.order()] == [(c, ids, s, t) for c, _, s, t, ids in queue.rows()]


def four():
    q = PatternQueue(QueuePolicy(4))
    for code, n, score, time in (("a", 3, 5.0, 9), ("b", 2, 8.0, 7), ("c", 2, 4.0, 8), ("d", 1, 6.0, 2)):
        q.restore(code, range(n), score, time)
    return q


def test_tail_mean_ties_and_victim():
    q = four()
    assert q.order.tail_mean() == 5.0 and q.passes(5.0)
    q.policy = QueuePolicy(4, ties="reject")
    assert not q.passes(5.0)
    q = four()
    q.offer(lambda: "e", 9, 5.0, 10)
    assert [r[0] for r in q.rows()] == ["a", "b", "c", "e"] and q.evicted == 1


def test_time_moves_only_when_the_set_grows():
    q = four()
    q.offer(lambda: "b", 0, 8.0, 50)
    assert dict((r[0], r[3]) for r in q.rows())["b"] == 7
    q.offer(lambda: "b", 5, 8.0, 51)
    assert dict((r[0], r[3]) for r in q.rows())["b"] == 51


def test_a_refused_sample_is_never_named():
    q = four()
    q.offer(lambda: pytest.fail("named"), 1, 4.9, 10)
    assert q.gated == 1


def test_large_queue_blocks():
    rng = random.Random(3)
    rows = [(f"p{rng.randrange(3000)}", rng.randrange(5), 1.0, t) for t in range(20_000)]
    q = iterate(rows, QueuePolicy(100_000))
    assert len(q.rows()) == len({c for c, *_ in rows}) and q.order.n == len(q.entries)
    keys = [(-n, -s, -t, c) for c, n, s, t, _ in q.rows()]
    assert keys == sorted(keys)
