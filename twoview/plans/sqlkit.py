"""Common table expressions in DuckDB SQL, for holding the library's results against an independent computation."""

from __future__ import annotations


def sqd(a: str, b: str, n: int) -> str:
    return f"list_sum([({a}[z]-{b}[z])*({a}[z]-{b}[z]) for z in range(1, {n + 1})])"


def vectors() -> str:
    return "v AS (SELECT vec_id, [x::DOUBLE for x in embedding] AS e FROM embeddings)"


def splits() -> str:
    return (
        "base AS (SELECT * FROM v WHERE vec_id % 10 >= 4), trn AS (SELECT * FROM v WHERE vec_id % 10 BETWEEN 1 AND 3), "
        "qry AS (SELECT vec_id AS qid, e AS q FROM v WHERE vec_id % 10 = 0)"
    )


def first_codebook(D: int, M: int, b: int) -> str:
    ds = D // M
    return (
        f"low AS (SELECT e, row_number() OVER (ORDER BY vec_id) - 1 AS i FROM trn QUALIFY i < {1 << b}), "
        f"cb AS (SELECT m::INTEGER AS m, i::INTEGER AS i, e[m*{ds}+1 : m*{ds}+{ds}] AS c FROM low, range({M}) r(m))"
    )


def nearest(D: int, M: int, source: str = "v", name: str = "enc", book: str = "cb") -> str:
    ds = D // M
    return (
        f"{name} AS (SELECT vec_id, m, i, d2 FROM (SELECT vec_id, m, i, c, {sqd(f'e[m*{ds}+1 : m*{ds}+{ds}]', 'c', ds)} AS d2 FROM {source}, {book}) "
        "QUALIFY row_number() OVER (PARTITION BY vec_id, m ORDER BY d2, i) = 1)"
    )


def lloyd(D: int, M: int, old: str, enc: str, new: str) -> str:
    ds = D // M
    return (
        f"{new}_p AS (SELECT n.m, n.i, d, avg(e[n.m*{ds}+d]) AS x FROM {enc} n JOIN trn USING (vec_id), range(1, {ds + 1}) r(d) GROUP BY n.m, n.i, d), "
        f"{new}_l AS (SELECT m, i, list(x ORDER BY d) AS moved FROM {new}_p GROUP BY m, i), "
        f"{new} AS (SELECT b.m, b.i, coalesce(l.moved, b.c) AS c FROM {old} b LEFT JOIN {new}_l l USING (m, i))"
    )


NUMBERINGS = {"identity": "i", "gray": "xor(i, i >> 1)", "affine": "(5*i+3) % {K}"}


def words(b: int, numbering: str = "identity", enc: str = "enc", name: str = "wrd") -> str:
    """One word: M * b is at most 64."""
    code = NUMBERINGS[numbering].format(K=1 << b)
    return (
        f"{name} AS (SELECT vec_id, (CASE WHEN u >= 9223372036854775808 THEN u - 18446744073709551616 ELSE u END)::BIGINT AS w "
        f"FROM (SELECT vec_id, sum(({code})::HUGEINT * (1::BIGINT << ({b}*m))::HUGEINT) AS u FROM {enc} GROUP BY vec_id))"
    )


def ham(a: str, b: str) -> str:
    return f"bit_count(xor({a}, {b}))::BIGINT"


def adc_pairs(D: int, M: int, keep: str = "") -> str:
    """Scores of all (or the kept) pairs, summed in the order of slices, so that equal codes have equal scores."""
    ds = D // M
    return (
        f"lut AS (SELECT qid, m, i, {sqd(f'q[m*{ds}+1 : m*{ds}+{ds}]', 'c', ds)} AS d FROM qry, cb), "
        f"adc AS (SELECT qid, vec_id, list_sum(list(d ORDER BY enc.m)) AS score FROM enc JOIN base USING (vec_id) JOIN lut ON lut.m = enc.m AND lut.i = enc.i {keep} GROUP BY qid, vec_id)"
    )


def top(source: str, k: int, score: str = "score") -> str:
    return f"SELECT qid, vec_id, round({score}, 6) AS score, row_number() OVER (PARTITION BY qid ORDER BY {score}, vec_id)::INTEGER AS rk FROM {source} QUALIFY rk <= {k}"


def with_(*parts: str) -> str:
    return "WITH " + ", ".join(parts) + " "
