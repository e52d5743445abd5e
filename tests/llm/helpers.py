"""Small tables with everything that may go wrong, for all corpus operators."""

import random

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega".split()
DOCS = "doc_id long, text string, lang string, source string, n_chars long, kept boolean, digest string, n int, root long, rate double, _row long, uid long, t long"


def prose(seed, n):
    r = random.Random(seed)
    return " ".join(f"{r.choice(WORDS)}{r.randrange(400)}" for _ in range(n))


def texts():
    """(id, text): empty, null, blank, short, long, copies, near copies, shared passages, odd characters, ties."""
    shared, near = prose(99, 70), prose(7, 120).split()
    out = [(1, None), (2, ""), (3, "  \t\n "), (4, "one"), (5, "one two"), (6, "One  TWO\tthree"), (7, "one two three"), (8, "one two\x0bthree "), (9, prose(1, 60)), (10, prose(1, 60)), (11, prose(1, 60).replace(" ", "  "))]
    out += [(12, prose(2, 40) + " " + shared + " " + prose(3, 30)), (13, prose(4, 20) + "\n" + shared), (14, shared + " " + prose(5, 55))]
    for i in range(8):
        w = list(near)
        for k in range(i):
            w[(k * 13 + 5) % len(w)] = f"edit{i}x{k}"
        out.append((20 + i, " ".join(w)))
    out += [(30, "é😀 日本語 ▁ a▁b  c " * 9), (31, "x" * 30_000), (32, prose(6, 6000)), (33, "a\n" * 500), (34, "row | cell | " * 60), (35, "<|endoftext|> and <s> </s> <0x41>. it's, O'Neil.. 3.14 ①. _."), (-5, prose(8, 30)), (36, "LOUD WORDS!! " * 40)]
    out += [(37, "mail joe.d+x@ex-1.example.org, ip 10.0.0.255 256.1.1.1, card 4111 1111 1111 1111, call +1 (988) 555-2485 4524132264652876 or (988) 555-2485")]
    return out


def documents(spark, rows=None, repeat=True):
    rows = texts() if rows is None else rows
    if repeat:
        rows = rows + [r for r in rows if r[0] in (9, 12)]
    return spark.createDataFrame([(i, t, "en", "src0", len(t or ""), True, "d", 1, 5, 0.5, 3, 4, 6) for i, t in rows], DOCS)
