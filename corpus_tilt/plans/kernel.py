"""The whole method in relational form, for the small byte model and the linear weight model.

Main model: logits theta(k, y) of the next byte y given the class k (high nibble) of the byte
before.  Weight model: score = alpha . phi, phi the shares of bytes by high nibble.  Losses,
gradients, Hessian products, inner products, all three outer steps, the filters and the loop are
joins and aggregates; ``Chain`` runs them on Spark and prints them for another engine.  Counts are
of whole texts; a batch is drawn first, and only its texts are counted by example.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from ..functions.bytecounts import byte_totals, nibble_shares, pair_counts, pair_totals
from ..functions.sqltext import DUCK, SPARK, Chain, Dialect, num

LARGE, SMALL = 256, 32
ETA_MAIN, ETA_WEIGHT, RHO, ETA_V, SMOOTH = 0.5, 0.1, 0.5, 0.1, 0.5


@dataclass
class Kernel:
    """Builds the steps of one task; ``target`` is a predicate over documents."""

    d: Dialect
    target: str = "lang = 'fr'"

    def __post_init__(self) -> None:
        self.c = Chain(self.d)
        self.base: dict[str, str] = {}  # of each step of ids, the batch (or all examples) they come from
        self._base()

    # --- data --------------------------------------------------------------------------------

    def _base(self) -> None:
        d, add = self.d, self.c.add
        hashed = d.hex_int("substr(md5(text), 1, 8)")
        body = "text as h" if d.name == "spark" else "hex(text) as h"
        add("ex", f"select doc_id as id, case when {self.target} then 1 else 0 end as side, case when {hashed} % 10 < 6 then 'train' when {hashed} % 10 < 8 then 'valid' else 'test' end as split, {body}, cast({d.octets('text')} as int) as nb from @documents where {d.octets('text')} >= 2", data=True)
        self.c.scans.add("ex")
        add("ys", f"select concat(substr('0123456789ABCDEF', cast(floor(i / 16) as int) + 1, 1), substr('0123456789ABCDEF', cast(i % 16 as int) + 1, 1)) as y from (select 0 as one) o, {d.series('256')} s")
        add("ks", f"select substr('0123456789ABCDEF', cast(i as int) + 1, 1) as k, cast(i as int) as j from (select 0 as one) o, {d.series('16')} s")
        add("grid", "select k, y from @ks cross join @ys")
        add("tasks", f"select side, split, k, y, cast(count(*) as bigint) as n from ({self._pairs('@ex', 1)}) p group by side, split, k, y", data=True, make=lambda t: pair_totals(t("ex"), 16))
        add("tot", "select side, split, k, y, cast(sum(n) as bigint) as n from @tasks group by side, split, k, y")
        add("th0", f"select g.k, g.y, (coalesce(c.n, 0e0) + {num(SMOOTH)}) / (coalesce(t.n, 0e0) + {num(256 * SMOOTH)}) as p, ln((coalesce(c.n, 0e0) + {num(SMOOTH)}) / (coalesce(t.n, 0e0) + {num(256 * SMOOTH)})) as t from @grid g left join (select k, y, cast(sum(n) as double) as n from @tot where side = 0 and split = 'train' group by k, y) c on c.k = g.k and c.y = g.y left join (select k, cast(sum(n) as double) as n from @tot where side = 0 and split = 'train' group by k) t on t.k = g.k")
        add("al0", f"select k, (j - 8) / {num(4)} as a from @ks")

    def _pairs(self, source: str, digits: int) -> str:
        """A row a byte but the first: the class of the byte before (its first hex digit, or both) and the byte."""
        cut = f"select id, side, split, regexp_extract_all(h, '..') as l from {source} z"
        return f"select id, side, split, substr(a, 1, {digits}) as k, y from (select id, side, split, unnest(l[1:len(l) - 1]) as a, unnest(l[2:]) as y from ({cut}) c) e"

    def _source(self, ids: str) -> tuple[str, str]:
        base = self.base.get(ids, ids)
        return base, "@ex" if base == "ex" else f"(select x.* from @ex x where x.id in (select id from @{base}))"

    def bg(self, ids: str, digits: int = 1) -> str:
        """Pair counts (id, k, y, n) of the whole texts of the batch that ``ids`` come from."""
        base, source = self._source(ids)
        name = f"bg_{base}" if digits == 1 else f"bg{digits}_{base}"
        if name not in self.c.steps:
            sql = f"select id, side, split, k, y, cast(count(*) as bigint) as n from ({self._pairs(source, digits)}) p group by id, side, split, k, y"
            self.c.add(name, sql, data=base in self.c.data, make=lambda t: pair_counts(_rows_of(t, base), 16**digits))
        return name

    def nk(self, ids: str) -> str:
        base = self.base.get(ids, ids)
        return self.c.add(f"nk_{base}", f"select id, k, cast(sum(n) as double) as nk from @{self.bg(ids)} group by id, k", data=base in self.c.data)

    def nx(self, ids: str) -> str:
        base = self.base.get(ids, ids)
        return self.c.add(f"nx_{base}", f"select id, cast(sum(n) as double) as nx from @{self.bg(ids)} group by id", data=base in self.c.data)

    def phi(self, ids: str) -> str:
        """Shares of bytes by high nibble, over whole texts."""
        base, source = self._source(ids)
        sql = f"select id, k, cast(count(*) as double) / max(nb) as share from (select id, nb, substr(unnest(regexp_extract_all(h, '..')), 1, 1) as k from {source} z) p group by id, k"
        return self.c.add(f"phi_{base}", sql, data=base in self.c.data, make=lambda t: nibble_shares(_rows_of(t, base)))

    def batch(self, name: str, side: int, split: str, seed: int | str, n: int, of: str = "ex") -> str:
        """A uniform batch without replacement: the least hashed numbers (a heap a partition, no sort of all)."""
        where = f"where side = {side} and split = '{split}'" if of == "ex" else ""
        self.base[name] = name if of == "ex" else self.base[of]
        return self.c.add(name, f"select id from (select id, {self.d.u01('id', seed)} as u from @{of} {where}) b order by u, id limit {n}")

    def ids(self, name: str, where: str) -> str:
        """All examples with a property."""
        self.base[name] = name
        self.c.scans.add(name)
        return self.c.add(name, f"select id, split from @ex where {where}", data=True)

    # --- weights and filters ---------------------------------------------------------------------

    def score(self, name: str, ids: str, alpha: str) -> str:
        """Scores ``name_s`` of any ids, and ``name`` with their softmax, for a batch (its rows meet in one window)."""
        self.base[name] = self.base[f"{name}_s"] = self.base.get(ids, ids)
        self.c.add(f"{name}_s", f"select b.id, sum(a.a * f.share) as s from @{ids} b join @{self.phi(ids)} f on f.id = b.id join @{alpha} a on a.k = f.k group by b.id", data=ids in self.c.data)
        return self.c.add(name, f"select id, s, e / sum(e) over () as w from (select id, s, exp(s - max(s) over ()) as e from @{name}_s) x")

    def gumbel(self, name: str, scored: str, seed: int | str, n: int) -> str:
        self.base[name] = self.base[scored]
        return self.c.add(name, f"select id from (select id, s - ln(-ln({self.d.u01('id', seed)})) as key from @{scored}) b order by key desc, id limit {n}")

    def top(self, name: str, scored: str, n: int) -> str:
        self.base[name] = self.base[scored]
        return self.c.add(name, f"select id from @{scored} order by s desc, id limit {n}")

    def iid(self, name: str, scored: str, seed: int | str, n: int) -> str:
        """n draws with replacement: sorted cumulative weights, and a range join with n uniforms."""
        self.c.add(f"{name}_c", f"select id, sum(w) over (order by id rows between unbounded preceding and current row) - w as lo, sum(w) over (order by id rows between unbounded preceding and current row) as hi from @{scored}")
        self.c.add(f"{name}_u", f"select i as draw, {self.d.u01('i', seed)} * (select max(hi) from @{name}_c) as u from (select 0 as one) o, {self.d.series(str(n))} s")
        return self.c.add(name, f"select c.id, cast(count(*) as bigint) as copies from @{name}_u u join @{name}_c c on u.u >= c.lo and u.u < c.hi group by c.id")

    def uniform_weights(self, name: str, ids: str) -> str:
        self.base[name] = self.base[ids]
        return self.c.add(name, f"select id, 1e0 / count(*) over () as w from @{ids}")

    # --- main model ------------------------------------------------------------------------------

    def grad(self, name: str, weights: str, theta: str) -> str:
        """Gradient of the weighted loss by (k, y); zero where a context does not occur."""
        self.c.add(f"{name}_m", f"select nk.k, sum(w.w * nk.nk / nx.nx) as m from @{weights} w join @{self.nk(weights)} nk on nk.id = w.id join @{self.nx(weights)} nx on nx.id = w.id group by nk.k")
        self.c.add(f"{name}_c", f"select b.k, b.y, sum(w.w * b.n / nx.nx) as c from @{weights} w join @{self.bg(weights)} b on b.id = w.id join @{self.nx(weights)} nx on nx.id = w.id group by b.k, b.y")
        return self.c.add(name, f"select t.k, t.y, coalesce(m.m, 0e0) * t.p - coalesce(c.c, 0e0) as g from @{theta} t left join @{name}_m m on m.k = t.k left join @{name}_c c on c.k = t.k and c.y = t.y")

    def hessian(self, name: str, grad: str, theta: str, v: str) -> str:
        """Weighted Hessian times v, from the context masses of ``grad`` (same weights)."""
        self.c.add(f"{name}_r", f"select t.k, sum(t.p * v.v) as r from @{theta} t join @{v} v on v.k = t.k and v.y = t.y group by t.k")
        return self.c.add(name, f"select t.k, t.y, coalesce(m.m, 0e0) * t.p * (v.v - r.r) as v from @{theta} t join @{v} v on v.k = t.k and v.y = t.y join @{name}_r r on r.k = t.k left join @{grad}_m m on m.k = t.k")

    def dots(self, name: str, ids: str, theta: str, v: str) -> str:
        """<gradient of each example's loss, v>, without any gradient of an example."""
        self.c.add(f"{name}_r", f"select t.k, sum(t.p * v.v) as r from @{theta} t join @{v} v on v.k = t.k and v.y = t.y group by t.k")
        self.c.add(f"{name}_a", f"select i.id, sum(nk.nk * r.r) as x from @{ids} i join @{self.nk(ids)} nk on nk.id = i.id join @{name}_r r on r.k = nk.k group by i.id")
        self.c.add(f"{name}_b", f"select i.id, sum(b.n * v.v) as x from @{ids} i join @{self.bg(ids)} b on b.id = i.id join @{v} v on v.k = b.k and v.y = b.y group by i.id")
        return self.c.add(name, f"select a.id, (a.x - b.x) / nx.nx as q from @{name}_a a join @{name}_b b on b.id = a.id join @{self.nx(ids)} nx on nx.id = a.id")

    def step(self, name: str, theta: str, grad: str, eta: float) -> str:
        """theta - eta g, and its probabilities."""
        moved = f"select t.k, t.y, t.t - {num(eta)} * g.g as t from @{theta} t join @{grad} g on g.k = t.k and g.y = t.y"
        return self.c.add(name, f"select k, y, e / sum(e) over (partition by k) as p, t from (select k, y, t, exp(t - max(t) over (partition by k)) as e from ({moved}) m) x")

    def nll(self, name: str, ids: str, theta: str) -> str:
        return self.c.add(name, f"select i.id, cast(sum(b.n) as bigint) as n_bytes, -sum(b.n * ln(t.p)) as nll from @{ids} i join @{self.bg(ids)} b on b.id = i.id join @{theta} t on t.k = b.k and t.y = b.y group by i.id", data=ids in self.c.data)

    # --- outer steps -------------------------------------------------------------------------------

    def utility(self, name: str, method: str, weights: str, specific: str, theta: str, v: str | None = None) -> str:
        """q of each example of ``weights``; the more, the more its weight should grow."""
        gs = self.grad(f"{name}_gs", self.uniform_weights(f"{name}_ws", specific), theta)
        gw = self.grad(f"{name}_gw", weights, theta)
        as_v = lambda n, g, by="": self.c.add(n, f"select k, y, g{by} as v from @{g}")
        if method == "unroll_first":
            return self.dots(name, weights, theta, as_v(f"{name}_v", gs, f" * {num(RHO)}"))
        if method == "unroll":
            ahead = self.step(f"{name}_u", theta, gw, RHO)
            gs = self.grad(f"{name}_ga", f"{name}_ws", ahead)
            return self.dots(name, weights, theta, as_v(f"{name}_v", gs, f" * {num(RHO)}"))
        if method == "cosine":
            self.c.add(f"{name}_l", f"select sqrt(sum(w.g * w.g)) as lw, sqrt(sum(s.g * s.g)) as ls, sum(w.g * s.g) as ws from @{gw} w join @{gs} s on s.k = w.k and s.y = w.y")
            self.c.add(f"{name}_v", f"select w.k, w.y, case when l.lw = 0 or l.ls = 0 then 0e0 else (s.g / l.ls - l.ws / (l.lw * l.ls) * w.g / l.lw) / l.lw end as v from @{gw} w join @{gs} s on s.k = w.k and s.y = w.y cross join @{name}_l l")
            return self.dots(name, weights, theta, f"{name}_v")
        if method == "implicit":
            hv = self.hessian(f"{name}_h", gw, theta, v)
            self.c.add(f"{name}_v2", f"select v.k, v.y, v.v - {num(ETA_V)} * (h.v + s.g) as v from @{v} v join @{hv} h on h.k = v.k and h.y = v.y join @{gs} s on s.k = v.k and s.y = v.y")
            self.dots(f"{name}_d", weights, theta, v)
            return self.c.add(name, f"select id, -q as q from @{name}_d")
        raise ValueError(method)

    def zero_v(self, name: str) -> str:
        return self.c.add(name, "select k, y, 0e0 as v from @grid")

    def alpha_step(self, name: str, alpha: str, weights: str, utility: str) -> str:
        self.c.add(f"{name}_q", f"select sum(w.w * q.q) as mean from @{weights} w join @{utility} q on q.id = w.id")
        self.c.add(f"{name}_d", f"select f.k, sum(w.w * (q.q - m.mean) * f.share) as d from @{weights} w join @{utility} q on q.id = w.id join @{self.phi(weights)} f on f.id = w.id cross join @{name}_q m group by f.k")
        return self.c.add(name, f"select a.k, a.a + {num(ETA_WEIGHT)} * coalesce(d.d, 0e0) as a from @{alpha} a left join @{name}_d d on d.k = a.k")

    # --- one step as all queries share it -----------------------------------------------------------

    def first(self) -> None:
        """A large generic batch with weights, a specific batch and a uniform sub-batch, all at step 0."""
        self.batch("big", 0, "train", 101, LARGE)
        self.score("sw", "big", "al0")
        self.batch("spec", 1, "train", 102, SMALL)
        self.batch("sub", 0, "train", 103, SMALL, of="big")
        self.score("ww", "sub", "al0")

    def loop(self, method: str, steps: int, filter_kind: str = "gumbel") -> tuple[str, str]:
        """``steps`` of the online loop; the names of the last theta and alpha."""
        theta, alpha, v = "th0", "al0", self.zero_v("v0") if method == "implicit" else None
        for t in range(1, steps + 1):
            big = self.batch(f"b{t}", 0, "train", f"{t}1", LARGE)
            spec = self.batch(f"p{t}", 1, "train", f"{t}2", SMALL)
            scored = self.score(f"s{t}", big, alpha)
            kept = self.gumbel(f"f{t}", scored, f"{t}4", SMALL) if filter_kind == "gumbel" else self.top(f"f{t}", scored, SMALL)
            sub = self.batch(f"u{t}", 0, "train", f"{t}3", SMALL, of=big)
            theta = self.step(f"th{t}", theta, self.grad(f"g{t}", self.uniform_weights(f"fw{t}", kept), theta), ETA_MAIN)
            weights = self.score(f"w{t}", sub, alpha)
            used = self.utility(f"q{t}", method, weights, spec, theta, v)
            alpha = self.alpha_step(f"al{t}", alpha, weights, used)
            v = f"q{t}_v2" if method == "implicit" else None
        return theta, alpha


def _rows_of(table: Callable, base: str):
    """The examples of a batch (a broadcast of its ids: as many as the batch has), of a set of examples, or all."""
    if base == "ex":
        return table("ex")
    ids = table(base).select("id")
    return table("ex").join(ids, "id", "left_semi")


def _out(build: Callable[[Kernel], str]) -> Callable[[Dialect], tuple[Chain, str]]:
    def made(d: Dialect) -> tuple[Chain, str]:
        k = Kernel(d)
        k.first()
        return k.c, k.c.add("out", build(k))

    return made


def _queries() -> dict[str, Callable[[Dialect], tuple[Chain, str]]]:
    q: dict[str, Callable[[Kernel], str]] = {}
    q["q_task_split"] = lambda k: "select side, split, cast(count(*) as bigint) as n, cast(count(distinct h) as bigint) as texts, cast(sum(nb) as bigint) as bytes from @ex group by side, split"
    def byte_counts(k: Kernel) -> str:
        k.c.add("byt", "select side, b, cast(count(*) as bigint) as n from (select side, unnest(regexp_extract_all(h, '..')) as b from @ex) z group by side, b", data=True, make=lambda t: byte_totals(t("ex")))
        return "select side, b, cast(sum(n) as bigint) as n from @byt group by side, b"

    q["q_byte_counts"] = lambda k: byte_counts(k)
    q["q_bigram_counts"] = lambda k: "select side, k, y, cast(sum(n) as bigint) as n from @tot group by side, k, y"
    q["q_class_features"] = lambda k: f"select id, k, {k.d.r6('share')} as share from @{k.phi('ex')}"
    q["q_base_model_prob"] = lambda k: f"select k, y, {k.d.r6('p')} as p from @th0"

    def doc_loss(k: Kernel) -> str:
        k.nll("l", "ex", "th0")
        return f"select id, n_bytes, {k.d.r6('nll')} as nll, {k.d.r6('nll / n_bytes')} as nll_per_byte from @l"

    q["q_doc_loss"] = doc_loss

    def nll_per_byte(k: Kernel) -> str:
        k.nll("l", "ex", "th0")
        return f"select e.side, e.split, cast(sum(l.n_bytes) as bigint) as n_bytes, {k.d.r6('sum(l.nll) / sum(l.n_bytes)')} as nll_per_byte, {k.d.r6('avg(l.nll / l.n_bytes)')} as doc_mean from @l l join @ex e on e.id = l.id group by e.side, e.split"

    q["q_nll_per_byte"] = nll_per_byte
    q["q_softmax_weights"] = lambda k: f"select id, {k.d.r6('s')} as score, {k.d.r6('w')} as w from @sw"

    def weighted_loss(k: Kernel) -> str:
        k.nll("l", "big", "th0")
        return f"select {k.d.r6('sum(w.w * l.nll / l.n_bytes)')} as weighted_loss, {k.d.r6('avg(l.nll / l.n_bytes)')} as uniform_loss from @sw w join @l l on l.id = w.id"

    q["q_weighted_loss"] = weighted_loss
    q["q_weight_concentration"] = lambda k: f"select {k.d.r6('sum(w) * sum(w) / sum(w * w)')} as ess, {k.d.r6('-sum(w * ln(w))')} as entropy, {k.d.r6('max(w)')} as top_weight from @sw"
    q["q_sample_uniform"] = lambda k: "select id from @big"
    q["q_filter_gumbel"] = lambda k: f"select id from @{k.gumbel('f', 'sw', 104, SMALL)}"
    q["q_filter_top"] = lambda k: f"select id from @{k.top('f', 'sw', SMALL)}"
    q["q_filter_iid"] = lambda k: f"select id, copies from @{k.iid('f', 'sw', 105, SMALL)}"
    q["q_filter_uniform"] = lambda k: "select id from @sub"

    def poisson(k: Kernel) -> str:
        # inclusion min(1, c w) with c = n / sum(w), then once more for what is not certain
        k.c.add("sure", f"select id, w, case when {num(SMALL)} * w >= 1e0 then 1 else 0 end as sure from @sw")
        k.c.add("rest", f"select ({num(SMALL)} - sum(sure)) / sum(case when sure = 0 then w else 0e0 end) as c from @sure")
        return f"select id, {k.d.r6('least(1e0, case when sure = 1 then 1e0 else w * c end)')} as inclusion from @sure cross join @rest where {k.d.u01('id', 106)} < least(1e0, case when sure = 1 then 1e0 else w * c end)"

    q["q_filter_poisson"] = poisson

    def diversity(k: Kernel) -> str:
        k.iid("f", "sw", 105, SMALL)
        return f"select cast(count(*) as bigint) as distinct_items, cast(sum(copies) as bigint) as draws, cast(max(copies) as bigint) as most_copies, {k.d.r6('sum(copies) * 1e0 / count(*)')} as mean_copies from @f"

    q["q_batch_diversity"] = diversity

    def filter_bias(k: Kernel, reps: int = 20) -> str:
        """Bias and spread of what each filter's plain mean says of the weighted loss, over repeated draws."""
        d = k.d
        k.nll("l", "big", "th0")
        k.c.add("per", "select w.id, w.s, w.w, l.nll / l.n_bytes as loss from @sw w join @l l on l.id = w.id")
        k.c.add("truth", "select sum(w * loss) as truth from @per")
        k.c.add("reps", f"select cast(i as int) as rep from (select 0 as one) o, {d.series(str(reps))} s")
        for kind, noise in (("gumbel", f"p.s - ln(-ln({d.u01("concat(r.rep, '/', p.id)", 401)}))"), ("top", "p.s"), ("uniform", d.u01("concat(r.rep, '/', p.id)", 402))):
            k.c.add(f"k_{kind}", f"select rep, avg(loss) as est from (select r.rep, p.loss, row_number() over (partition by r.rep order by {noise} desc, p.id) as turn from @per p cross join @reps r) x where turn <= {SMALL} group by rep")
        k.c.add("cum", "select loss, sum(w) over (order by id rows between unbounded preceding and current row) - w as lo, sum(w) over (order by id rows between unbounded preceding and current row) as hi from @per")
        k.c.add("draws", f"select rep, {d.u01("concat(rep, '/', draw)", 403)} * (select max(hi) from @cum) as u from (select r.rep, cast(i as int) as draw from @reps r, {d.series(str(SMALL))} s) y")
        k.c.add("k_iid", "select d.rep, avg(c.loss) as est from @draws d join @cum c on d.u >= c.lo and d.u < c.hi group by d.rep")
        return " union all ".join(f"select '{kind}' as kind, {d.r6('avg(e.est) - max(t.truth)')} as bias, {d.r6('stddev_pop(e.est)')} as spread from @k_{kind} e cross join @truth t" for kind in ("gumbel", "top", "uniform", "iid"))

    q["q_filter_bias"] = filter_bias

    def grad_norms(k: Kernel) -> str:
        k.grad("gs", k.uniform_weights("us", "spec"), "th0")
        k.grad("gw", "ww", "th0")
        return f"select 'specific' as side, {k.d.r6('sqrt(sum(g * g))')} as norm from @gs union all select 'weighted' as side, {k.d.r6('sqrt(sum(g * g))')} as norm from @gw"

    q["q_grad_norms"] = grad_norms

    def alignment(k: Kernel) -> None:
        k.grad("gs", k.uniform_weights("us", "spec"), "th0")
        k.c.add("vs", "select k, y, g as v from @gs")
        k.dots("al", "big", "th0", "vs")

    def align(k: Kernel) -> str:
        alignment(k)
        return f"select id, {k.d.r6('q')} as a from @al"

    def align_norm(k: Kernel) -> str:
        alignment(k)
        k.c.add("norm", "select sqrt(sum(g * g)) as n from @gs")
        return f"select id, {k.d.r6('q / n')} as a_norm from @al cross join @norm"

    q["q_alignment"], q["q_alignment_norm"] = align, align_norm

    def rates(k: Kernel, pairs: int = 4, size: int = 24) -> None:
        for i in range(pairs):
            for side, tag in ((1, "s"), (0, "g")):
                ids = k.batch(f"r{tag}{i}", side, "test", f"7{tag}{i}", size)
                g = k.grad(f"rg{tag}{i}", k.uniform_weights(f"ru{tag}{i}", ids), "th0")
                k.c.add(f"rn{tag}{i}", f"select k, y, g / (select sqrt(sum(g * g)) from @{g}) as v from @{g}")
            k.c.add(f"rv{i}", f"select s.k, s.y, s.v - g.v as v from @rns{i} s join @rng{i} g on g.k = s.k and g.y = s.y")
            k.batch(f"rx{i}", 1, "valid", f"8s{i}", 64)
            k.batch(f"ry{i}", 0, "valid", f"8g{i}", 64)
            k.dots(f"rp{i}", f"rx{i}", "th0", f"rv{i}")
            k.dots(f"rq{i}", f"ry{i}", "th0", f"rv{i}")
        each = " union all ".join(f"select 's' as origin, {i} as pair, id, q from @rp{i} union all select 'g' as origin, {i} as pair, id, q from @rq{i}" for i in range(pairs))
        k.c.add("rates", each)

    def sar_gar(k: Kernel) -> str:
        rates(k)
        return f"select {k.d.r6('''avg(case when origin = 's' then case when q > 0 then 1e0 else 0e0 end end)''')} as sar, {k.d.r6('''avg(case when origin = 'g' then case when q < 0 then 1e0 else 0e0 end end)''')} as gar, cast(count(distinct pair) as bigint) as n_pairs from @rates"

    def mix(k: Kernel) -> str:
        rates(k, 1)
        return f"select origin, cast(count(*) as bigint) as n, {k.d.r6('avg(q)')} as mean_move from @rates group by origin"

    q["q_sar_gar"], q["q_mix_diagnostic"] = sar_gar, mix

    def utility(method: str) -> Callable[[Kernel], str]:
        def build(k: Kernel) -> str:
            v = None
            if method == "implicit":  # two recursions first
                k.utility("i1", "implicit", "ww", "spec", "th0", k.zero_v("v0"))
                k.utility("i2", "implicit", "ww", "spec", "th0", "i1_v2")
                v = "i2_v2"
            k.utility("q", method, "ww", "spec", "th0", v)
            return f"select id, {k.d.r6('q')} as q from @q"

        return build

    def alpha(method: str) -> Callable[[Kernel], str]:
        def build(k: Kernel) -> str:
            utility(method)(k)
            k.alpha_step("al", "al0", "ww", "q")
            return f"select k, {k.d.r6('a')} as a from @al"

        return build

    for name, method in (("unroll1", "unroll_first"), ("unroll_exact", "unroll"), ("cosine", "cosine"), ("implicit", "implicit")):
        q[f"q_utility_{name}"] = utility(method)
    for name in ("unroll", "cosine", "implicit"):
        q[f"q_alpha_step_{name}"] = alpha(name)

    def sparse(k: Kernel) -> str:
        k.gumbel("f", "sw", 104, SMALL)
        k.step("th1", "th0", k.grad("g", k.uniform_weights("fw", "f"), "th0"), ETA_MAIN)
        return f"select k, y, {k.d.r6('t')} as t from @th1"

    def dense(k: Kernel) -> str:
        k.step("th1", "th0", k.grad("g", "sw", "th0"), ETA_MAIN)
        return f"select k, y, {k.d.r6('t')} as t from @th1"

    q["q_main_step_sparse"], q["q_main_step_dense"] = sparse, dense

    def hvp(k: Kernel) -> str:
        k.grad("gs", k.uniform_weights("us", "spec"), "th0")
        k.c.add("vs", "select k, y, g as v from @gs")
        k.hessian("h", k.grad("gw", "ww", "th0"), "th0", "vs")
        return f"select k, y, {k.d.r6('v')} as hv from @h"

    q["q_hessian_product"] = hvp

    def two_steps(method: str) -> Callable[[Kernel], str]:
        def build(k: Kernel) -> str:
            _, alpha_name = k.loop(method, 2)
            return f"select k, {k.d.r6('a')} as a from @{alpha_name}"

        return build

    q["q_bilevel_2steps"] = two_steps("cosine")
    q["q_bilevel_2steps_unroll"] = two_steps("unroll")
    q["q_bilevel_2steps_implicit"] = two_steps("implicit")

    def reweight(k: Kernel) -> None:
        k.uniform_weights("uw", "sub")
        k.utility("q", "unroll_first", "uw", "spec", "th0")
        k.c.add("raw", f"select w.id, greatest(0e0, w.w + {num(ETA_WEIGHT)} * q.q) as w from @uw w join @q q on q.id = w.id")
        k.c.add("rw", "select id, case when (select sum(w) from @raw) > 0 then w / (select sum(w) from @raw) else 1e0 / (select count(*) from @raw) end as w from @raw")

    def reweight_weights(k: Kernel) -> str:
        reweight(k)
        return f"select id, {k.d.r6('w')} as w from @rw"

    q["q_reweight_weights"] = reweight_weights

    def loss_input(k: Kernel) -> str:
        k.nll("l", "big", "th0")
        x = "(nll / n_bytes)"
        s = f"0.7e0 * tanh(1.5e0 * {x} - 3e0) - 0.4e0 * tanh(0.5e0 * {x})"
        k.c.add("ls", f"select id, {s} as s from @l")
        return f"select id, {k.d.r6('s')} as score, {k.d.r6('exp(s) / (select sum(exp(s)) from @ls)')} as w from @ls"

    q["q_loss_input_score"] = loss_input

    def counted(k: Kernel, name: str, weight: str) -> str:
        """A model counted from training pairs with a weight by side."""
        k.c.add(f"{name}_n", f"select k, y, sum(n * ({weight})) as n from @tot where split = 'train' group by k, y")
        k.c.add(f"{name}_k", f"select k, sum(n) as n from @{name}_n group by k")
        return k.c.add(name, f"select g.k, g.y, (coalesce(c.n, 0e0) + {num(SMOOTH)}) / (coalesce(t.n, 0e0) + {num(256 * SMOOTH)}) as p from @grid g left join @{name}_n c on c.k = g.k and c.y = g.y left join @{name}_k t on t.k = g.k")

    def held_out(k: Kernel, theta: str) -> str:
        k.ids("held", "side = 1 and split = 'test'")
        k.nll("hl", "held", theta)
        return f"select cast(sum(n_bytes) as bigint) as n_bytes, {k.d.r6('sum(nll) / sum(n_bytes)')} as nll_per_byte from @hl"

    q["q_generic_only"] = lambda k: held_out(k, counted(k, "mg", "case when side = 0 then 1e0 else 0e0 end"))
    q["q_mixing_model"] = lambda k: held_out(k, counted(k, "mm", "case when side = 1 then 9e0 else 1e0 end"))
    q["q_finetune_nll"] = lambda k: held_out(k, counted(k, "mf", "case when side = 1 then 1e0 else 0.02e0 end"))

    def rank_methods(k: Kernel) -> str:
        k.ids("held", "side = 1 and split <> 'train'")
        parts = []
        for name, weight in (("generic_only", "case when side = 0 then 1e0 else 0e0 end"), ("mixing", "case when side = 1 then 9e0 else 1e0 end"), ("finetuned", "case when side = 1 then 1e0 else 0.02e0 end")):
            k.nll(f"n_{name}", "held", counted(k, f"m_{name}", weight))
            parts.append(f"select '{name}' as method, h.split, sum(n.nll) / sum(n.n_bytes) as nll from @n_{name} n join @held h on h.id = n.id group by h.split")
        return f"select method, split, {k.d.r6('nll')} as nll_per_byte, cast(rank() over (partition by split order by nll) as bigint) as place from ({' union all '.join(parts)}) r"

    q["q_rank_methods"] = rank_methods

    def contrastive(k: Kernel) -> str:
        k.ids("pool", "side = 0 and split = 'train'")
        k.nll("l0", "pool", counted(k, "m0", "case when side = 0 then 1e0 else 0e0 end"))
        k.nll("l1", "pool", counted(k, "m1", "case when side = 1 then 1e0 else 0.02e0 end"))
        return f"select id, {k.d.r6('gain')} as gain from (select a.id, (a.nll - b.nll) / a.n_bytes as gain from @l0 a join @l1 b on b.id = a.id) g order by g.gain desc, id limit 64"

    q["q_contrastive_topk"] = contrastive

    def classifier(k: Kernel, steps: int = 3) -> str:
        alpha_name = k.c.add("c0", "select k, 0e0 as a from @ks")
        k.batch("cs", 1, "train", 301, 64)
        k.batch("cg", 0, "train", 302, 64)
        k.c.add("cb", "select id, 1e0 as y from @cs union all select id, 0e0 as y from @cg")
        feats = k.c.add("cf", f"select * from @{k.phi('cs')} union all select * from @{k.phi('cg')}")
        for t in range(steps):
            k.c.add(f"cp{t}", f"select b.id, b.y, 1e0 / (1e0 + exp(-sum(a.a * f.share))) as p from @cb b join @{feats} f on f.id = b.id join @{alpha_name} a on a.k = f.k group by b.id, b.y")
            k.c.add(f"cd{t}", f"select f.k, avg_sum / (select count(*) from @cb) as d from (select f.k, sum((p.y - p.p) * f.share) as avg_sum from @cp{t} p join @{feats} f on f.id = p.id group by f.k) f")
            alpha_name = k.c.add(f"c{t + 1}", f"select a.k, a.a + 4e0 * coalesce(d.d, 0e0) as a from @{alpha_name} a left join @cd{t} d on d.k = a.k")
        return alpha_name

    def classifier_step(k: Kernel) -> str:
        return f"select k, {k.d.r6('a')} as a from @{classifier(k)}"

    def classifier_topk(k: Kernel) -> str:
        name = classifier(k)
        k.ids("gen", "side = 0 and split = 'train'")
        k.score("gs", "gen", name)
        return f"select id, {k.d.r6('1e0 / (1e0 + exp(-s))')} as p from @gs_s order by s desc, id limit 64"

    q["q_classifier_step"], q["q_classifier_topk"] = classifier_step, classifier_topk

    def retrain(k: Kernel, name: str, alphas: list[str]) -> str:
        """The main model trained anew on the same large batches under given weights, one a step."""
        theta = "th0"
        for t, alpha in enumerate(alphas, 1):
            kept = k.gumbel(f"{name}f{t}", k.score(f"{name}s{t}", f"b{t}", alpha), f"{t}4", SMALL)
            theta = k.step(f"{name}th{t}", theta, k.grad(f"{name}g{t}", k.uniform_weights(f"{name}w{t}", kept), theta), ETA_MAIN)
        return theta

    def trajectories(k: Kernel) -> str:
        """Held-out loss under the learned weights, the last ones frozen, and the learned ones in another order."""
        theta, last = k.loop("cosine", 2)
        k.ids("held", "side = 1 and split = 'test'")
        models = {"learned": theta, "final": retrain(k, "fin", [last, last]), "shuffled": retrain(k, "shu", ["al1", "al0"])}
        for name, model in models.items():
            k.nll(f"n_{name}", "held", model)
        return " union all ".join(f"select '{name}' as weights, {k.d.r6('sum(nll) / sum(n_bytes)')} as nll_per_byte from @n_{name}" for name in models)

    q["q_frozen_vs_shuffled"] = trajectories

    def costs(k: Kernel) -> str:
        """Evaluations of one step, counted from the rows that it touches."""
        k.loop("cosine", 1)
        n = lambda step: f"(select count(*) from @{step})"
        k.c.add("tally", f"select {n('s1')} as weight_fwd, {n('f1')} as main_bwd, {n('u1')} as outer_bwd, {n('p1')} as specific_bwd, (select count(*) from @al1) as moved")
        return f"select cast(weight_fwd as bigint) as weight_fwd, cast(main_bwd as bigint) as main_bwd, cast(outer_bwd as bigint) as outer_bwd, cast(specific_bwd as bigint) as specific_bwd, {k.d.r6('weight_fwd * 1e0 / main_bwd')} as ratio, {k.d.r6('1e0 - main_bwd * 1e0 / weight_fwd')} as unseen_share from @tally"

    q["q_cost_counts"] = costs

    def transfer(k: Kernel) -> str:
        # weights learned with the small model select data for the large one (256 contexts)
        _, alpha_name = k.loop("cosine", 2)
        k.ids("gen", "side = 0 and split = 'train'")
        k.score("gs", "gen", alpha_name)
        k.c.add("sel", "select id from @gs order by s desc, id limit 200")
        k.base["sel"] = "sel"
        k.ids("held", "side = 1 and split = 'test'")
        for name, ids in (("big2", "sel"), ("test2", "held")):
            k.c.add(name, f"select k, y, cast(sum(n) as double) as n from @{k.bg(ids, 2)} group by k, y")
        k.c.add("tot2", "select k, sum(n) as n from @big2 group by k")
        return f"select cast(sum(t.n) as bigint) as n_bytes, {k.d.r6('''-sum(t.n * ln((coalesce(b.n, 0e0) + 0.5e0) / (coalesce(o.n, 0e0) + 128e0))) / sum(t.n)''')} as nll_per_byte from @test2 t left join @big2 b on b.k = t.k and b.y = t.y left join @tot2 o on o.k = t.k"

    q["q_transfer_nll"] = transfer
    return {name: _out(build) for name, build in q.items()}


QUERIES = _queries()


def spark_query(name: str):
    def run(spark, sf_dir: str):
        chain, final = QUERIES[name](SPARK)
        return chain.run(spark, sf_dir, final)

    return run


def oracle_text(name: str) -> str:
    chain, final = QUERIES[name](DUCK)
    return chain.text(final)
