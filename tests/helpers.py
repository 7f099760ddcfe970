import numpy as np

from ctxloom.operators.stream import Flat, array_stream


def flat(*sequences):
    codes = np.array([x for s in sequences for x in s], np.int64)
    starts = np.concatenate([[0], np.cumsum([len(s) for s in sequences])]).astype(np.int64)
    return Flat(codes, starts, np.arange(len(sequences)), np.zeros(len(sequences), np.int64))


def stream_of(spark, sequences, m):
    rows = [(i, None if s is None else [int(x) for x in s]) for i, s in enumerate(sequences)]
    return array_stream(spark.createDataFrame(rows, "id long, syms array<int>"), "syms", m, ("id",))


def markov(rng, table, n):
    table, x, out = np.asarray(table), 0, []
    for _ in range(n):
        x = int(rng.choice(len(table), p=table[x]))
        out.append(x)
    return out
