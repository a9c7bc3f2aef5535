"""DuckDB text for the registered queries, in plain shapes: expansion instead of sweeps, products instead of hash keys."""

from __future__ import annotations

from dataclasses import asdict, dataclass

from ..functions.hashing import CODEC, POOL, PRIME, ROOT, salted
from ..functions.params import GridParams, hot_cutoff
from ..sources.contacts import THETA

ROUTERS = "(SELECT {0}, row_number() OVER (ORDER BY {0}) - 1 AS router FROM (SELECT DISTINCT {0} FROM {1}))"


def theta(fixture: str) -> str:
    """The fixture's threshold as SQL, by the rows of its table."""
    rule = THETA[fixture]
    if isinstance(rule, int):
        return str(rule)
    name, rows, spread, least, most = rule
    return f"(SELECT least({most}, greatest({least}, CAST(floor(count(*) / {rows} + {spread} * sqrt(count(*) / {rows})) AS BIGINT))) FROM {name})"


def cutoff(m: int, theta: int | str) -> str:
    return repr(hot_cutoff(m, theta)) if isinstance(theta, int) else f"({m} * (1 - exp(-CAST({theta} AS DOUBLE) / {m})))"


@dataclass(frozen=True)
class SqlGrid(GridParams):
    """Grid parameters whose threshold is SQL."""

    theta: str = "1024"

    @classmethod
    def of(cls, p: GridParams, theta: str) -> SqlGrid:
        return cls(**asdict(p) | {"theta": theta})

    @property
    def cutoff(self) -> str:
        return cutoff(self.m, self.theta)

    def validate(self) -> SqlGrid:
        GridParams(**asdict(self) | {"theta": 1}).validate()
        return self


def mixed(x: str, consts: tuple[int, int, int, int]) -> str:
    a1, b1, a2, b2 = consts
    h = f"((({x}) * {a1} + {b1}) % {PRIME})"
    return f"((xor({h}, {h} >> 15) * {a2} + {b2}) % {PRIME})"


def rec(x: str, m: int, salt: int = 0) -> str:
    return f"({mixed(x, salted(salt))} % {m})"


def root(x: str, w: int) -> str:
    return f"({mixed(x, ROOT)} & {(1 << w) - 1})"


def codec(x: str) -> str:
    return f"(({x}) * {CODEC} & 4294967295)"


def key32(x: str) -> str:
    return f"CAST('0x' || substr(md5({x}), 1, 8) AS BIGINT)"


def event_slot(x: str = "ts") -> str:
    return f"((epoch_us({x}) - epoch_us(TIMESTAMP '2024-01-01')) // 720000000)"


def ship_slot(x: str = "l_shipdate") -> str:
    return f"((epoch_us({x}) - epoch_us(TIMESTAMP '1995-01-01')) // 2592000000000)"


_K = "CAST(json_extract_string(props, '$.k') AS BIGINT)"
_TOKENS = "unnest(list_distinct(regexp_extract_all(lower(text), '[a-z]+')))"
_DOCS = "SELECT {0} AS core, doc_id AS opp, doc_id // 10 AS slot, router FROM (SELECT doc_id, source, {1} AS token FROM documents {2}) JOIN {3} USING (source)"
_LO = "lineitem JOIN orders ON l_orderkey = o_orderkey"
CONTACTS = {
    "F1": f"SELECT {codec(_K)} AS core, user_id AS opp, {event_slot()} AS slot, router FROM events JOIN {ROUTERS.format('event_type', 'events')} USING (event_type)",
    "F2": f"SELECT {codec('user_id')} AS core, {_K} AS opp, {event_slot()} AS slot, router FROM events JOIN {ROUTERS.format('event_type', 'events')} USING (event_type)",
    "F3": f"SELECT {codec('l_suppkey')} AS core, l_partkey AS opp, {ship_slot()} AS slot, l_linenumber % 4 AS router FROM lineitem",
    "F4": f"SELECT {codec('l_suppkey')} AS core, o_custkey AS opp, {ship_slot('o_orderdate')} AS slot, l_linenumber % 4 AS router FROM {_LO}",
    "F5": f"SELECT {codec('o_custkey')} AS core, l_partkey AS opp, {ship_slot('o_orderdate')} AS slot, o_orderkey % 4 AS router FROM {_LO}",
    "F6": _DOCS.format(key32("token"), _TOKENS, "", ROUTERS.format("source", "documents")),
    "F7": f"""SELECT {key32("regexp_extract(url, '^[a-z]+://([^/]+)', 1)")} AS core, {key32("href")} AS opp, page_id // 10 AS slot, page_id % 4 AS router
              FROM (SELECT page_id, url, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)""",
    "F8": f"""SELECT {key32("token")} AS core, conv_id AS opp, turn AS slot, router FROM (SELECT conv_id, turn, role, {_TOKENS} AS token FROM conversations)
              JOIN {ROUTERS.format('role', 'conversations')} USING (role)""",
    "F9": _DOCS.format(key32("token"), _TOKENS, "WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)", ROUTERS.format("source", "(SELECT source FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1))")),
}


class With:
    """Named parts of a statement, in order."""

    def __init__(self):
        self.parts: list[tuple[str, str]] = []

    def add(self, name: str, sql: str) -> With:
        if name not in dict(self.parts):
            self.parts.append((name, sql))
        return self

    def contacts(self, fixture: str, name: str = "c") -> With:
        return self.add(name, CONTACTS[fixture])

    def select(self, sql: str) -> str:
        return "WITH " + ",\n".join(f"{n} AS MATERIALIZED ({s})" for n, s in self.parts) + "\n" + sql


def _by(by: tuple[str, ...], alias: str = "") -> str:
    return "".join(f"{alias}{b}, " for b in by)


def same(a: str, b: str, by: tuple[str, ...]) -> str:
    return "".join(f" AND {a}.{x} = {b}.{x}" for x in by)


def expanded(src: str, n: int, k: int) -> str:
    """Contacts once for every sliding window that has their slot."""
    return f"SELECT win, core, opp, slot FROM (SELECT *, unnest(range(greatest(slot - {k - 1}, 0), least(slot, {n - k}) + 1)) AS win FROM {src} WHERE slot >= 0 AND slot < {n})"


def fixed(src: str, n: int, k: int) -> str:
    return f"SELECT *, slot // {k} AS win FROM {src} WHERE slot >= 0 AND slot < {n - n % k}"


def est(m: int, touched: str = "touched") -> str:
    return f"round(-{m}.0 * ln(greatest({m} - {touched}, 1) / {m}.0), 6)"


def grid(src: str, p: GridParams, by: tuple[str, ...] = ()) -> str:
    shift = f"(i * {p.d})" if p.literal_shift else f"(greatest(i - 1, 0) * {p.d})"
    return f"""SELECT {_by(by)}i AS row_id, CASE WHEN i = 0 THEN rt ELSE xor(core >> {shift}, rt) & {p.mask} END AS col_id, rec, max(slot) AS last_slot
        FROM (SELECT {_by(by)}core, slot, {root('core', p.w)} AS rt, {rec('opp', p.m)} AS rec FROM {src}), (SELECT unnest(range({p.r})) AS i) GROUP BY ALL"""


def hot(g: str, p: GridParams, by: tuple[str, ...] = ()) -> str:
    return f"SELECT {_by(by)}row_id, col_id, count(*) AS touched FROM {g} GROUP BY ALL HAVING count(*) >= {p.cutoff}"


def chains(h: str, p: GridParams, upto: int | None = None, by: tuple[str, ...] = ()) -> str:
    last = p.r - 1 if upto is None else upto
    sql = f"SELECT {_by(by, 'h0.')}" + ", ".join(f"h{i}.col_id AS c{i}" for i in range(last + 1)) + f" FROM (SELECT * FROM {h} WHERE row_id = 0) h0"
    for i in range(1, last + 1):
        fits = f" AND (xor(h0.col_id, h{i - 1}.col_id) >> {p.d}) = (xor(h0.col_id, h{i}.col_id) & {p.overlap_mask})" if i > 1 else ""
        sql += f" JOIN (SELECT * FROM {h} WHERE row_id = {i}) h{i} ON true{same('h0', f'h{i}', by)}{fits}"
    return sql


def addresses(ch: str, p: GridParams, by: tuple[str, ...] = ()) -> str:
    cols = ", ".join(f"c{i}" for i in range(p.r))
    core = " | ".join(f"(xor(c{i}, c0) << {p.shift(i)})" for i in range(1, p.r))
    if p.literal_shift:
        return f"SELECT * FROM (SELECT {_by(by)}{cols}, high | low AS core FROM (SELECT *, {core} AS high FROM {ch}), (SELECT unnest(range({1 << p.d})) AS low) WHERE high < 4294967296) WHERE {root('core', p.w)} = c0"
    keep = ["true"] + ["core < 4294967296"] * p.pad_check + [f"{root('core', p.w)} = c0"] * p.root_check
    return f"SELECT * FROM (SELECT {_by(by)}{cols}, {core} AS core FROM {ch}) WHERE {' AND '.join(keep)}"


def verified(ad: str, g: str, p: GridParams, by: tuple[str, ...] = (), least: float | None = None) -> str:
    cols = ", ".join(f"c{i}" for i in range(p.r))
    cut = p.cutoff if least is None else least
    return f"""SELECT {_by(by)}{cols}, core, count(*) AS touched FROM (SELECT {_by(by, 'a.')}{cols}, core, rec
        FROM (SELECT *, unnest([{cols}]) AS col_id, unnest(range({p.r})) AS row_id FROM {ad}) a JOIN {g} g ON g.row_id = a.row_id AND g.col_id = a.col_id{same('g', 'a', by)}
        GROUP BY ALL HAVING count(*) = {p.r}) GROUP BY ALL HAVING count(*) >= {cut}"""


def report(v: str, p: GridParams, by: tuple[str, ...] = ()) -> str:
    return f"SELECT {_by(by)}core, touched, {est(p.m)} AS est, touched >= {p.m} AS saturated FROM (SELECT {_by(by)}core, max(touched) AS touched FROM {v} GROUP BY ALL)"


def regain(w: With, src: str, p: GridParams, by: tuple[str, ...] = (), tag: str = "", g: str | None = None) -> With:
    """Adds grid, hot cells, chains, addresses and the report `found<tag>`."""
    if g is None:
        g = f"grid{tag}"
        w.add(g, grid(src, p, by))
    w.add(f"hot{tag}", hot(g, p, by)).add(f"chains{tag}", chains(f"hot{tag}", p, None, by)).add(f"adr{tag}", addresses(f"chains{tag}", p, by))
    return w.add(f"ver{tag}", verified(f"adr{tag}", g, p, by)).add(f"found{tag}", report(f"ver{tag}", p, by))


def fan(src: str, by: tuple[str, ...] = ()) -> str:
    return f"SELECT {_by(by)}core, count(DISTINCT opp) AS fan_out FROM {src} GROUP BY ALL"


def accuracy(found: str, truth: str, by: tuple[str, ...] = (), more: str = "") -> str:
    """Rates from counts of two anti joins."""
    keys = f"(SELECT DISTINCT {', '.join(by)} FROM (SELECT {', '.join(by)} FROM {found} UNION ALL SELECT {', '.join(by)} FROM {truth}))" if by else "(SELECT 1 AS one)"
    match = lambda t: " AND ".join([f"{t}.{b} = k.{b}" for b in by] or ["true"])
    none = lambda a, b: f"NOT EXISTS (SELECT 1 FROM {b} y WHERE y.core = {a}.core{same('y', a, by)})"
    return f"""SELECT {more}{_by(by)}n_true, n_found, n_false, n_missed, CASE WHEN n_true > 0 THEN round(n_false / n_true, 6) END AS fpr,
        CASE WHEN n_true > 0 THEN round(n_missed / n_true, 6) END AS fnr, CASE WHEN n_true > 0 THEN round((n_false + n_missed) / n_true, 6) END AS tfr
        FROM (SELECT {_by(by, 'k.')}(SELECT count(*) FROM {truth} t WHERE {match('t')}) AS n_true, (SELECT count(*) FROM {found} f WHERE {match('f')}) AS n_found,
        (SELECT count(*) FROM {found} f WHERE {match('f')} AND {none('f', truth)}) AS n_false,
        (SELECT count(*) FROM {truth} t WHERE {match('t')} AND {none('t', found)}) AS n_missed FROM {keys} k)"""


def crt(w: With, src: str, m: int, theta: int | str, moduli: tuple[int, ...], by: tuple[str, ...] = (), tag: str = "crt") -> With:
    """Products of hot cells, a sum of multiples for the address, and one test of all rows at the end plus one after two rows."""
    cut = cutoff(m, theta)
    w.add(f"{tag}_g", " UNION ALL ".join(f"SELECT DISTINCT {_by(by)}{i} AS row_id, core % {q} AS col_id, {rec('opp', m)} AS rec FROM {src}" for i, q in enumerate(moduli)))
    w.add(f"{tag}_h", f"SELECT {_by(by)}row_id, col_id FROM {tag}_g GROUP BY ALL HAVING count(*) >= {cut}")
    w.add(f"{tag}_b", f"SELECT g.* FROM {tag}_g g JOIN {tag}_h h ON g.row_id = h.row_id AND g.col_id = h.col_id{same('g', 'h', by)}")
    w.add(f"{tag}_2", f"SELECT {_by(by, 'a.')}a.col_id AS c0, b.col_id AS c1 FROM {tag}_b a JOIN {tag}_b b ON a.row_id = 0 AND b.row_id = 1 AND a.rec = b.rec{same('a', 'b', by)} GROUP BY ALL HAVING count(*) >= {cut}")
    w.add(
        f"{tag}_3",
        f"""SELECT {_by(by, 'p.')}c0, c1, d.col_id AS c2, count(*) AS touched FROM {tag}_2 p JOIN {tag}_b a ON a.row_id = 0 AND a.col_id = c0{same('a', 'p', by)}
        JOIN {tag}_b b ON b.row_id = 1 AND b.col_id = c1 AND b.rec = a.rec{same('b', 'p', by)} JOIN {tag}_b d ON d.row_id = 2 AND d.rec = a.rec{same('d', 'p', by)}
        GROUP BY ALL HAVING count(*) >= {cut}""",
    )
    total = moduli[0] * moduli[1] * moduli[2]
    x = " + ".join(f"c{i}::HUGEINT * {total // q * pow(total // q, -1, q)}::HUGEINT" for i, q in enumerate(moduli))
    return w.add(f"{tag}_found", f"SELECT {_by(by)}core, touched, {est(m)} AS est, touched >= {m} AS saturated FROM (SELECT {_by(by)}touched, CAST(({x}) % {total} AS BIGINT) AS core FROM {tag}_3) WHERE core < 4294967296")


def slices(w: With, src: str, p: GridParams, by: tuple[str, ...] = (), tag: str = "sl") -> With:
    rows = range(1, p.r)
    w.add(f"{tag}_g", " UNION ALL ".join(f"SELECT DISTINCT {_by(by)}{i} AS row_id, (core >> {p.shift(i)}) & {p.mask} AS col_id, {rec('opp', p.m)} AS rec FROM {src}" for i in rows))
    w.add(f"{tag}_h", f"SELECT {_by(by)}row_id, col_id FROM {tag}_g GROUP BY ALL HAVING count(*) >= {p.cutoff}")
    sql = f"SELECT {_by(by, 'h1.')}" + ", ".join(f"h{i}.col_id AS c{i}" for i in rows) + f", {' | '.join(f'(h{i}.col_id << {p.shift(i)})' for i in rows)} AS core FROM (SELECT * FROM {tag}_h WHERE row_id = 1) h1"
    for i in rows[1:]:
        sql += f" JOIN (SELECT * FROM {tag}_h WHERE row_id = {i}) h{i} ON (h{i - 1}.col_id >> {p.d}) = (h{i}.col_id & {p.overlap_mask}){same('h1', f'h{i}', by)}"
    w.add(f"{tag}_c", f"SELECT * FROM ({sql}) WHERE core < 4294967296")
    cols = ", ".join(f"c{i}" for i in rows)
    w.add(
        f"{tag}_v",
        f"""SELECT {_by(by)}core, count(*) AS touched FROM (SELECT {_by(by, 'a.')}core, rec FROM (SELECT *, unnest([{cols}]) AS col_id, unnest(range(1, {p.r})) AS row_id FROM {tag}_c) a
        JOIN {tag}_g g ON g.row_id = a.row_id AND g.col_id = a.col_id{same('g', 'a', by)} GROUP BY ALL HAVING count(*) = {p.r - 1}) GROUP BY ALL HAVING count(*) >= {p.cutoff}""",
    )
    return w.add(f"{tag}_found", f"SELECT {_by(by)}core, touched, {est(p.m)} AS est, touched >= {p.m} AS saturated FROM {tag}_v")


def pool(w: With, src: str, bits: int, s: int, theta: int | str, by: tuple[str, ...] = (), tag: str = "po") -> With:
    spot = lambda v: f"({mixed(f'xor(core, ({v}) * 2654435761 & 4294967295)', POOL)} % {bits})"
    w.add(f"{tag}_p", f"SELECT DISTINCT {_by(by)}{spot(rec('opp', s))} AS bit FROM {src}")
    w.add(f"{tag}_l", f"SELECT DISTINCT {_by(by)}core FROM {src}")
    w.add(f"{tag}_q", f"SELECT {_by(by, 'l.')}core, count(*) AS touched FROM (SELECT {_by(by)}core, {spot('v')} AS bit FROM {tag}_l, (SELECT unnest(range({s})) AS v)) l JOIN {tag}_p p ON l.bit = p.bit{same('l', 'p', by)} GROUP BY ALL")
    w.add(f"{tag}_f", f"SELECT {_by(by)}1.0 - count(*) / {bits}.0 AS free FROM {tag}_p GROUP BY ALL" if by else f"SELECT 1.0 - count(*) / {bits}.0 AS free FROM {tag}_p")
    e = f"round({s}.0 * ln(free) - {s}.0 * ln(greatest({s} - touched, 1) / {s}.0), 6)"
    return w.add(f"{tag}_found", f"SELECT * FROM (SELECT {_by(by, 'q.')}core, touched, {e} AS est FROM {tag}_q q JOIN {tag}_f f ON true{same('q', 'f', by)}) WHERE est >= {theta}")
