"""the overlay's mining forms only the branches of its prefix tree, and picks what the whole tree would."""

import random
import time

from graphwin.operators.overlay import mine_chunk


def by_whole_tree(owners: list[int], lists: list[list[int]], first_node: int) -> tuple[list[list[int]], list[tuple[int, list[int]]]]:
    """Greedy picks from a prefix tree of the chunk: items by falling frequency, each tree path shared by several owners
    saves (owners - 1) * (items - 1) - 1 additions."""
    counts: dict[int, int] = {}
    for items in lists:
        for i in items:
            counts[i] = counts.get(i, 0) + 1
    tree: dict[tuple[int, ...], list[int]] = {}
    ordered = [sorted((i for i in items if counts[i] > 1), key=lambda i: (-counts[i], i)) for items in lists]
    children: list[dict[int, int]] = [{}]
    users: list[list[int]] = [[]]
    depth, parent, label = [0], [-1], [0]
    for row, items in enumerate(ordered):
        at = 0
        for i in items:
            nxt = children[at].get(i)
            if nxt is None:
                nxt = children[at][i] = len(children)
                children.append({}), users.append([]), depth.append(depth[at] + 1), parent.append(at), label.append(i)
            at = nxt
            users[at].append(row)
    picks = sorted(((len(users[t]) - 1) * (depth[t] - 1) - 1, t) for t in range(1, len(users)) if len(users[t]) > 1)[::-1]
    taken, made, out = set(), [], [set(items) for items in lists]
    for saving, t in picks:
        rows = [r for r in users[t] if r not in taken]
        if saving <= 0 or (len(rows) - 1) * (depth[t] - 1) - 1 <= 0:
            continue
        group, at = [], t
        while at:
            group.append(label[at])
            at = parent[at]
        node = first_node - len(made)
        made.append((node, sorted(group)))
        for r in rows:
            taken.add(r)
            out[r] -= set(group)
            out[r].add(node)
    tree.clear()
    return [sorted(s) for s in out], made


def test_same_picks_as_the_whole_tree():
    rng = random.Random(7)
    for n, top, share in ((0, 5, 0.5), (1, 5, 0.5), (12, 6, 0.6), (40, 30, 0.8), (40, 30, 0.1), (60, 25, 0.95)):
        for _ in range(8):
            lists = [sorted(i * 10**12 - 3 * 10**12 for i in range(top) if rng.random() < share) for _ in range(n)]
            lists += rng.sample(lists, n // 4)
            owners = list(range(len(lists)))
            assert mine_chunk(owners, lists, -(1 << 44) - 1) == by_whole_tree(owners, lists, -(1 << 44) - 1)


def test_dense_lists_take_a_fraction_of_the_tree():
    """Lists like those of suppliers that share an order: most of all items each."""
    rng = random.Random(1)
    lists = [sorted(i for i in range(1000) if rng.random() < 0.84) for _ in range(500)]
    began = time.time()
    got = mine_chunk(list(range(500)), lists, -1)
    mid = time.time()
    assert got == by_whole_tree(list(range(500)), lists, -1)
    assert (mid - began) * 2 < time.time() - mid
