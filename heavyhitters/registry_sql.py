"""SQL of the summary methods, as chains of plain CTEs, written apart from the DataFrame code.

Every chain starts from `s(keys, block_id, item)` and works on several k at once.
"""

from __future__ import annotations

from collections.abc import Sequence

from .sources.workloads import SQL


def workload(name: str, p: int) -> str:
    """(item, block_id) of a workload dealt by its key."""
    return f"SELECT item, (key % {p})::INTEGER AS block_id FROM ({SQL[name]}) WHERE item IS NOT NULL"


class Chain:
    """CTEs of the local phase; methods add levels and finish with a select."""

    def __init__(self, source: str, ks: Sequence[int], keys: Sequence[str] = (), blocks: int = 0):
        self.keys, self.ks = list(keys), ks
        self.K = [*keys, "k"]
        k = ", ".join(self.K)
        base = "".join(f"{x}, " for x in keys)
        every = f"SELECT {base}k, range::INTEGER AS block_id FROM {'(SELECT DISTINCT ' + ', '.join(keys) + ' FROM c), ' if keys else ''}ks, range({blocks})" if blocks else f"SELECT DISTINCT {base}k, block_id FROM c, ks"
        self.ctes = [
            f"s AS ({source})",
            f"c AS (SELECT {base}block_id, item, count(*)::BIGINT AS est FROM s GROUP BY ALL)",
            f"ks(k) AS (VALUES {', '.join(f'({x}::INTEGER)' for x in ks)})",
            f"l0 AS (SELECT {k}, block_id, item, est, 0::BIGINT AS err FROM (SELECT *, row_number() OVER (PARTITION BY {k}, block_id ORDER BY est DESC, item) AS rn FROM c, ks) WHERE rn <= k)",
            f"b0 AS ({every})",
            f"n0 AS (SELECT {k}, block_id, coalesce(sum(est), 0)::BIGINT AS n FROM b0 LEFT JOIN c USING ({base}block_id) GROUP BY ALL)",
            self._header(0),
        ]
        self.k, self.base, self.level = k, base, 0

    def _header(self, i: int) -> str:
        k = ", ".join(self.K)
        return f"h{i} AS (SELECT {k}, block_id, n, coalesce(nz, 0)::BIGINT AS nz, (CASE WHEN nz = k THEN m ELSE 0 END)::BIGINT AS m, coalesce(te, 0)::BIGINT AS te FROM n{i} LEFT JOIN (SELECT {k}, block_id, count(*) AS nz, min(est) AS m, sum(est) AS te FROM l{i} GROUP BY ALL) USING ({k}, block_id))"

    def merge(self, parent: str) -> Chain:
        """One merge of the blocks with the same `parent` (an expression of block_id)."""
        i, k = self.level, self.k
        j = i + 1
        self.ctes += [
            f"o{j} AS (SELECT {k}, {parent} AS block_id, item, sum(est - m) AS e, sum(err - m) AS r FROM l{i} JOIN h{i} USING ({k}, block_id) GROUP BY ALL)",
            f"t{j} AS (SELECT {k}, {parent} AS block_id, sum(n)::BIGINT AS n, sum(m)::BIGINT AS d FROM h{i} GROUP BY ALL)",
            f"l{j} AS (SELECT {k}, block_id, item, (e + d)::BIGINT AS est, (r + d)::BIGINT AS err FROM (SELECT *, row_number() OVER (PARTITION BY {k}, block_id ORDER BY e DESC, item) AS rn FROM o{j} JOIN t{j} USING ({k}, block_id)) WHERE rn <= k)",
            f"n{j} AS (SELECT {k}, block_id, n FROM t{j})",
            self._header(j),
        ]
        self.level = j
        return self

    def flat(self) -> Chain:
        return self.merge("0")

    def tree(self, p: int, fan_in: int = 2) -> Chain:
        while p > 1:
            self.merge(f"block_id // {fan_in}")
            p = -(-p // fan_in)
        return self

    def report(self) -> Chain:
        i, k = self.level, self.k
        self.ctes.append(f"rep AS (SELECT {k}, item, est, err, est - err AS lower, CASE WHEN est - err >= n // k + 1 THEN 'guaranteed' ELSE 'potential' END AS status FROM l{i} JOIN h{i} USING ({k}, block_id) WHERE est >= n // k + 1)")
        return self

    def deficit(self, p: int, fan_in: int = 2, name: str = "dm") -> Chain:
        """The baseline from the local summaries: d<i>(counters), e<i>(headers with delta), then `name`."""
        k = self.k
        self.ctes += [f"d0 AS (SELECT {k}, block_id, item, est - m AS est FROM l0 JOIN h0 USING ({k}, block_id) WHERE est > m)", f"e0 AS (SELECT {k}, block_id, n, m AS delta FROM h0)"]
        i = 0
        while p > 1:
            j = i + 1
            self.ctes += [
                f"a{j} AS (SELECT {k}, block_id // {fan_in} AS block_id, item, sum(est)::BIGINT AS est FROM d{i} GROUP BY ALL)",
                f"r{j} AS (SELECT *, row_number() OVER (PARTITION BY {k}, block_id ORDER BY est DESC, item) AS rn FROM a{j})",
                f"x{j} AS (SELECT {k}, block_id, max(CASE WHEN rn = k THEN est ELSE 0 END) AS cut FROM r{j} GROUP BY ALL)",
                f"d{j} AS (SELECT {k}, block_id, item, est - cut AS est FROM r{j} JOIN x{j} USING ({k}, block_id) WHERE rn <= k AND est > cut)",
                f"y{j} AS (SELECT {k}, block_id // {fan_in} AS block_id, sum(n)::BIGINT AS n, sum(delta)::BIGINT AS delta FROM e{i} GROUP BY ALL)",
                f"e{j} AS (SELECT {k}, block_id, n, (delta + coalesce(cut, 0))::BIGINT AS delta FROM y{j} LEFT JOIN x{j} USING ({k}, block_id))",
            ]
            i, p = j, -(-p // fan_in)
        self.ctes.append(f"{name} AS (SELECT {k}, item, est, n, delta FROM d{i} JOIN e{i} USING ({k}, block_id))")
        return self

    def truth(self) -> Chain:
        base, k = self.base, self.k
        using = f"USING ({', '.join(self.keys)})" if self.keys else ""
        totals = f"SELECT {base}sum(cnt)::BIGINT AS n FROM tr" + (f" GROUP BY {', '.join(self.keys)}" if self.keys else "")
        self.ctes += [
            f"tr AS (SELECT {base}item, sum(est)::BIGINT AS cnt FROM c GROUP BY ALL)",
            f"tn AS (SELECT * FROM ({totals}), ks)",
            f"fq AS (SELECT {k}, count(*) AS n_true FROM tr {'JOIN tn ' + using if using else 'CROSS JOIN tn'} WHERE cnt >= n // k + 1 GROUP BY ALL)",
        ]
        return self

    def metrics(self, method: str, reported: str) -> str:
        """Select of one method's measures; `reported` has (K, item, est)."""
        k = self.k
        on = ", ".join([*self.keys, "item"])
        return f"""SELECT '{method}' AS method, {k}, n, coalesce(n_true, 0)::BIGINT AS n_true, coalesce(n_reported, 0)::BIGINT AS n_reported, coalesce(n_hit, 0)::BIGINT AS n_hit,
coalesce(total_error, 0)::BIGINT AS total_error, are, (n_hit / n_reported)::DOUBLE AS precision, coalesce(coalesce(n_hit, 0) / nullif(n_true, 0), 1.0)::DOUBLE AS recall
FROM tn LEFT JOIN fq USING ({k}) LEFT JOIN (SELECT {k}, count(*) AS n_reported, count(*) FILTER (WHERE cnt >= n // k + 1) AS n_hit, sum(abs(cnt - est)) AS total_error, avg(abs(cnt - est) / cnt) AS are
FROM (SELECT {k}, item, q.est, cnt FROM {reported} q JOIN tr USING ({on})) JOIN tn USING ({k}) GROUP BY ALL) USING ({k})"""

    def select(self, text: str) -> str:
        return "WITH " + ",\n".join(self.ctes) + "\n" + text


def exact(source: str, k: int, cols: str = "item, cnt") -> str:
    return f"WITH s AS ({source}), c AS (SELECT item, count(*)::BIGINT AS cnt FROM s WHERE item IS NOT NULL GROUP BY item) SELECT {cols} FROM c WHERE cnt >= (SELECT sum(cnt)::BIGINT FROM c) // {k} + 1"


def accuracy(source: str, ks: Sequence[int], p: int, keys: Sequence[str] = ()) -> str:
    chain = Chain(source, ks, keys).flat().report().deficit(p).truth()
    return chain.select(chain.metrics("summary", "rep") + "\nUNION ALL\n" + chain.metrics("deficit", "dm"))
