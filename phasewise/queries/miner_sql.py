"""The phased miner in SQL: one step of the recursion is one phase of a stream, and a run is a fold over the
phase's input.  Written from the method's rules, apart from the engine, to check it."""

from __future__ import annotations


def miner_sql(points: str, *, k: int, num: int | None, runs: int, outlier_phases: int = 2, gamma: float = 34, beta: float = 34, growth: str = "every_phase", seed: int = 1, caps: tuple[float | None, float | None] = (None, None), floor: float | None = None) -> str:
    """CTEs up to ``result(stream_key, phase, cid, cx, cw, verdicts, log)``, one row a stream.

    ``points`` is SQL of (stream_key, ordinal, id, x); ``num`` None takes all the rest as a phase's input;
    ``caps``: a cost cap and a median cap in place of the phase's own, ``floor``: a first floor in place of the
    points' own, where given."""
    m = 1 + 4 * (gamma + beta)
    price = f"coalesce(floor, 0) / ({k} * (1 + ln(n)))"
    cost_cap = str(caps[0]) if caps[0] else f"coalesce(4 * floor * {m}, 'infinity'::double)"
    median_cap = str(caps[1]) if caps[1] else f"4 * {k} * (1 + ln(n)) * {m}"
    rest = f"pts[nxt + 1 : {f'nxt + {num}' if num else 'n'}]"
    head = f"r <= {num}" if num else "true"
    draw = f"cast(('0x' || substr(md5('{seed}|' || run || '|' || phase || '|' || e.id), 1, 8)) as bigint) / 4294967296.0"
    load = "case when price > 0 then q.t * e.w / price when q.t * e.w > 0 then 1.0 else 0.0 end"
    near = "list_transform([list_transform(a.x, lambda v: abs(v - e.x))], lambda d: {'t': list_min(d), 'at': list_position(d, list_min(d))})"
    stop = "{'x': a.x, 'id': a.id, 'w': a.w, 'g': a.g, 'service': a.service, 'ssq': a.ssq, 'far': a.far, 'read': a.read, 'reason': %s}"
    opened = "{'x': list_append(a.x, e.x), 'id': list_append(a.id, e.id), 'w': list_append(a.w, e.w), 'g': list_append(a.g, false), 'service': a.service, 'ssq': a.ssq, 'far': a.far, 'read': a.read + 1, 'reason': 'end'}"
    joined = "{'x': a.x, 'id': a.id, 'w': list_transform(a.w, lambda v, j: case when j = q.at then v + e.w else v end), 'g': list_transform(a.g, lambda v, j: v or j = q.at), 'service': a.service + q.t * e.w, 'ssq': a.ssq + e.w * q.t * q.t, 'far': greatest(a.far, q.t), 'read': a.read + 1, 'reason': 'end'}"
    over = "case when a.service + price * (len(a.x) + 1) > cost_cap then 'cost' when len(a.x) + 1 > median_cap then 'medians' end"
    fold = f"""case when a.reason <> 'end' then a else list_transform({near}, lambda q:
      case when len(a.x) = 0 or {draw} < least({load}, 1.0)
           then case when {over} is not null then {stop % over} else {opened} end
           when a.service + q.t * e.w + price * len(a.x) > cost_cap then {stop % "'cost'"} else {joined} end)[1] end"""
    nothing = "{'x': []::double[], 'id': []::bigint[], 'w': []::double[], 'g': []::boolean[], 'service': 0.0::double, 'ssq': 0.0::double, 'far': 0.0::double, 'read': 0::bigint, 'reason': 'end'}"
    candidate = "struct(id bigint, first int, age int, score int, w double, verdict varchar, settled int)[]"
    log = "struct(phase int, floor double, price double, winner_run int, points_in bigint, points_read bigint, medians_out int, new_medians int, service_cost double, total_cost double, ssq double, max_dist double, stop_reason varchar, least double, most double, fewest int, most_medians int)[]"
    aged = """list_transform(cands, lambda c: case
        when not list_contains(cid[1:least(won.read, len(cid))], c.id) then c
        when not list_contains(won.id, c.id) then {'id': c.id, 'first': c.first, 'age': c.age, 'score': c.score, 'w': c.w, 'verdict': 'absorbed', 'settled': phase}
        else list_transform([{'age': c.age + 1, 'score': c.score + (not won.g[list_position(won.id, c.id)])::int}], lambda y: {'id': c.id, 'first': c.first, 'age': y.age, 'score': y.score, 'w': won.w[list_position(won.id, c.id)],
               'verdict': case when y.age < %d then null when y.score = %d then 'outlier' else 'inlier' end, 'settled': phase})[1] end)""" % (outlier_phases, outlier_phases)
    first = "select stream_key, %r::double as floor from s" % floor if floor is not None else f"select a.stream_key, min(abs(a.x - b.x)) / {beta} as floor from few a join few b on a.stream_key = b.stream_key and a.o < b.o group by 1"
    grown = {"every_phase": f"floor * {beta}", "on_breach": f"case when won.reason <> 'end' then floor * {beta} else floor end", "none": "floor"}[growth]
    return f"""with recursive points as ({points}),
s as (select stream_key, count(*) as n, list({{'id': id::bigint, 'x': x::double, 'w': 1.0::double}} order by ordinal) as pts from points group by 1),
firsts as (select stream_key, x, min(ordinal) as o from (select *, row_number() over (partition by stream_key order by ordinal) as r from points) where {head} group by 1, 2),
few as (select * from firsts qualify row_number() over (partition by stream_key order by o) <= {k + 1}),
floors as ({first}),
t(stream_key, n, pts, nxt, phase, floor, cid, cx, cw, cands, verdicts, log) using key (stream_key) as (
  select s.stream_key, n, pts, 0::bigint, 0, floor::double, []::bigint[], []::double[], []::double[], []::{candidate}, []::{candidate}, []::{log}
  from s left join floors on s.stream_key = floors.stream_key
  union
  select stream_key, n, pts, nxt + fresh_read, phase, {grown}, list_concat(list_transform(kept, lambda j: won.id[j]), cid[won.read + 1:]), list_concat(list_transform(kept, lambda j: won.x[j]), cx[won.read + 1:]), list_concat(list_transform(kept, lambda j: won.w[j]), cw[won.read + 1:]),
    list_concat(list_filter(aged, lambda c: c.verdict is null), list_transform(list_filter(range(1, len(won.id) + 1), lambda j: not won.g[j] and not list_contains(list_transform(aged, lambda c: c.id), won.id[j])),
      lambda j: {{'id': won.id[j], 'first': phase, 'age': 1, 'score': 1, 'w': won.w[j], 'verdict': null::varchar, 'settled': null::int}})),
    list_concat(verdicts, list_filter(aged, lambda c: c.verdict is not null)),
    list_append(log, {{'phase': phase, 'floor': coalesce(floor, 0), 'price': price, 'winner_run': run, 'points_in': {"len(its) - len(cid)" if num else "fresh_read + (won.reason <> 'end')::int"}, 'points_read': fresh_read, 'medians_out': len(kept) + greatest(len(cid) - won.read, 0),
      'new_medians': len(list_filter(won.id, lambda v: not list_contains(cid, v))), 'service_cost': won.service, 'total_cost': won.service + price * len(won.x), 'ssq': won.ssq, 'max_dist': won.far, 'stop_reason': won.reason, 'least': list_min(list_transform(passes, lambda p: p.service + price * len(p.x))), 'most': list_max(list_transform(passes, lambda p: p.service + price * len(p.x))), 'fewest': list_min(list_transform(passes, lambda p: len(p.x))), 'most_medians': list_max(list_transform(passes, lambda p: len(p.x)))}})
  from (select *, list_filter(range(1, len(won.id) + 1), lambda j: not list_contains(list_transform(list_filter(aged, lambda c: c.verdict = 'outlier'), lambda c: c.id), won.id[j])) as kept, greatest(won.read - len(cid), 0) as fresh_read
    from (select *, {aged} as aged
      from (select *, passes[best.run + 1] as won, best.run as run
        from (select *, list_min(list_transform(passes, lambda p, j: {{'read': -p.read, 'total': p.service + price * len(p.x), 'run': j - 1}})) as best
          from (select *, list_transform(range(0, {runs}), lambda run: list_reduce(its, lambda a, e: {fold}, {nothing})) as passes
            from (select stream_key, n, pts, nxt, phase + 1 as phase, floor, cid, cx, cw, cands, verdicts, log, {price} as price, {cost_cap} as cost_cap, {median_cap} as median_cap,
                    list_concat(list_transform(range(1, len(cid) + 1), lambda j: {{'id': cid[j], 'x': cx[j], 'w': cw[j]}}), {rest}) as its
                  from t where nxt < n))))))
), result as (
  select stream_key, phase, cid, cx, cw, list_concat(verdicts, list_transform(cands, lambda c: {{'id': c.id, 'first': c.first, 'age': c.age, 'score': c.score, 'w': c.w, 'verdict': 'pending', 'settled': phase}})) as verdicts, log from t
)
"""


EVENTS = "select 'all' as stream_key, row_number() over (order by event_id) as ordinal, event_id as id, value as x from events"
USERS = "select user_id::varchar as stream_key, row_number() over (partition by user_id order by event_id) as ordinal, event_id as id, value as x from events"
VERDICTS = "select stream_key, v.id as median_id, v.first as first_phase, v.settled as settled_phase, v.age, v.score, v.w as weight, v.verdict from (select stream_key, unnest(verdicts) as v from result)"
PHASE_LOG = "select stream_key, l.phase, round(l.floor, 2) as floor, round(l.price, 2) as price, l.winner_run, l.points_in, l.points_read, l.points_in - l.points_read as unread, l.medians_out, l.new_medians, round(l.service_cost, 4) as service_cost, round(l.total_cost, 2) as total_cost, round(l.ssq, 5) as ssq, round(l.max_dist, 6) as max_dist, l.stop_reason from (select stream_key, unnest(log) as l from result)"
MEDIANS = "select stream_key, unnest(cid) as median_id, unnest(cx) as x, unnest(cw) as weight from result"
