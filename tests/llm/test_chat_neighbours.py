import hashlib
import random

import numpy as np

from chaincores.llm import chat, neighbours
from chaincores.llm.queries import tokenizer_file

TOK = tokenizer_file("byte_bpe_50k.json")
PARTS = ["\\", "###", "</turn>", "### user: ", "a", " ", "\n", "é😀", ":", "<", "<|endoftext|>", "</turn", "字", "\t  ", ">"]


def digest(turns):
    said = [t for r, t in turns if r == "assistant"]
    return len(turns), hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest(), sum(map(len, said)), hashlib.sha256("".join(said).encode()).hexdigest()


def test_round_trip(spark, monkeypatch):
    rng = random.Random(5)
    rows, want = [], {}
    for conv in range(120):
        turns = [(rng.choice(["user", "assistant", "sys:tem\\", ""]), "".join(rng.choice(PARTS) for _ in range(rng.randrange(30)))) for _ in range(rng.randrange(1, 9))]
        want[conv] = digest(turns)
        rows += [(conv, i, r or None, t or None, 1) for i, (r, t) in enumerate(turns)]
    want[-7] = digest([("user", "\\### Assistant: </turn> ok"), ("assistant", "\\### Assistant: </turn> ok")])
    want[None] = digest([("assistant", "x y"), ("assistant", "x y")])
    rows += [(None, 1, "assistant", "x y", 1)] * 2
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, n_turns int")
    got = {r.conv_id: (r.n_turns, r.turns_sha256, r.loss_chars, r.loss_sha256) for r in chat.formatted_corpus(df, TOK).collect()}
    assert got == want
    assert chat.formatted_corpus(df.limit(0), TOK).count() == 1
    monkeypatch.setattr(chat, "SEGMENT", 10)
    assert [t for p in [[("a", "b c")], [("assistant", " d\n")]] for t in chat._encoder(TOK).encode(chat.render(p)[0]).ids] == chat._encoder(TOK).encode(chat.render([("a", "b c"), ("assistant", " d\n")])[0]).ids


def test_runs_of_turns_equal_the_whole(spark, monkeypatch):
    """A long conversation encoded in runs of turns has the tokens, offsets, masks and digest of one encoded whole."""
    rng = random.Random(9)
    rows = []
    for conv in range(3):
        for i in range(150):
            rows.append((conv, i, rng.choice(["user", "assistant"]), "".join(rng.choice(PARTS) for _ in range(rng.randrange(25)))))
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")

    def joined():
        out = {}
        for r in sorted(chat.format_conversations(df, TOK).collect(), key=lambda r: (r.conv_id, r.part)):
            text, ids, starts, ends, loss, ss, se = out.setdefault(r.conv_id, ("", [], [], [], [], [], []))
            n = len(text)
            out[r.conv_id] = text + r.text, ids + r.token_ids, starts + [x + n for x in r.token_starts], ends + [x + n for x in r.token_ends], loss + r.loss, ss + [x + n for x in r.span_starts], se + [x + n for x in r.span_ends]
        return out, sorted(map(tuple, chat.formatted_corpus(df, TOK).collect()))

    whole = joined()
    monkeypatch.setattr(chat, "SEGMENT", 200)
    assert chat.format_conversations(df, TOK).where("part > 3").count() > 0
    assert joined() == whole


def brute(rows, qs, top):
    out = set()
    ids = np.array([i for i, _ in rows])
    x = np.array([v for _, v in rows], float)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    for q in qs:
        s = np.round(x @ x[list(ids).index(q)], 12)
        best = sorted(((-v, i) for v, i in zip(s, ids, strict=True) if i != q))[:top]
        out |= {(int(q), r + 1, int(i)) for r, (_, i) in enumerate(best)}
    return out


def test_search_finds_the_nearest(spark):
    rng = np.random.default_rng(2)
    rows = [(i, rng.normal(size=24).tolist()) for i in range(3000)]
    rows += [(i, rows[7][1]) for i in range(3000, 3400)]  # a very common vector
    df = spark.createDataFrame(rows + rows[:5] + [(-1, None), (-2, [0.0] * 24), (-3, [float("nan")] * 24), (-4, [None] * 24), (None, [1.0] * 24), (-5, [1.0, 2.0])], "vec_id long, embedding array<double>")
    qs = [i for i in range(0, 3400, 40)]
    got = neighbours.search(df, df.where(f"vec_id % 40 = 0"), top=5).collect()
    want = brute(rows, qs, 5)
    found = {(r.query_id, r.rank, r.vec_id) for r in got}
    assert len(got) == len(want)
    near = {(q, i) for q, _, i in want}
    assert len(near & {(q, i) for q, _, i in found}) / len(near) >= 0.9
    common = {(q, r, i) for q, r, i in want if q >= 3000}
    assert common <= found  # ties go to the smaller id


def test_scores_order_exactly(spark):
    """Cosines that differ in the last digits are told apart; multiples by powers of two and repeated rows tie; the least of a query's vectors asks."""
    rng = np.random.default_rng(3)
    base = rng.normal(size=16)
    rows = [(0, base.tolist())] + [(i, (base + 1e-7 * rng.normal(size=16)).tolist()) for i in range(1, 40)]
    rows += [(i, (np.array(rows[5][1]) * 2.0**i).tolist()) for i in range(40, 44)] + [(0, (base + 1).tolist())]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = [(r.rank, r.vec_id) for r in neighbours.search(df, df.where("vec_id = 0"), top=8).orderBy("rank").collect()]
    q = np.array(min(v for i, v in rows if i == 0))
    cos = lambda v: float((q * v).sum() / (np.linalg.norm(q) * np.linalg.norm(v)))
    want = sorted((-round(cos(np.array(v)), 15), i) for i, v in rows if i)[:8]
    scores = {i: cos(np.array(v)) for i, v in rows if i}
    assert [r for r, _ in got] == list(range(1, 9))
    assert all(scores[a] >= scores[b] - 4e-16 for (_, a), (_, b) in zip(got, got[1:]))
    assert min(scores[i] for _, i in got) >= -want[-1][0] - 4e-16
    tied = [i for _, i in got if i == 5 or i >= 40]
    assert tied == sorted(tied)


def test_search_few_rows(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0], 1), (50, [-1.0, 1e-3], 1), (51, [0.0, 1e300], 1)], "vec_id long, embedding array<double>, score int")
    got = sorted((r.query_id, r.rank, r.vec_id) for r in neighbours.search(df, df.where("vec_id % 50 = 0")).collect())
    assert got == [(0, 1, 51), (0, 2, 50), (50, 1, 51), (50, 2, 0)]
    assert neighbours.search(df.limit(0), df.limit(0)).count() == 0
