"""The script language: same classes as the builder's, and its static checks."""

import pytest

from tickspace import models
from tickspace.operators.tick import naive_sql, tick
from tickspace.plans.agents import invert
from tickspace.plans.script import ScriptError, check_script, compile_script, explain_script, parse_script
from tickspace.queries import FISH_SCRIPT


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.fixture(scope="module")
def fish(spark):
    data = [(i, (i * 37) % 1500 - 700, (i * 91) % 1300 - 600, i % 7 - 3, i % 5 - 2) for i in range(80)] + [(200, 0, 0, 1, 1), (201, 0, 0, 1, 1)]
    return spark.createDataFrame(data, "id bigint, x bigint, y bigint, vx bigint, vy bigint")


def test_script_means_what_the_builder_means(fish):
    world = compile_script(FISH_SCRIPT)
    want = rows(tick({"fish": fish}, models.basic_fish(), 3)["fish"])
    assert rows(tick({"fish": fish}, world, 3)["fish"]) == want
    assert rows(tick({"fish": fish}, invert(world), 3)["fish"]) == want
    assert naive_sql(world, {"fish": "SELECT 1"}, 1, "SELECT 1").startswith("WITH")


def test_methods_private_and_stages(fish):
    world = compile_script("""
        agent fish {
          state x; state y; private state vx; state vy = seen;
          effect n : count; effect seen : max from 0;
          def near(d, r) = abs(d) <= r;
          each fish within x [-200, 200], y [-200, 200] where near(other.x - self.x, 100) and near(other.y - self.y, 100) { n <- self.vx; }
          stage 1 each fish within x [-200, 200], y [-200, 200] { other.seen <- self.n; }
        }""")
    got = {r["id"]: r["vy"] for r in tick({"fish": fish}, world, 0)["fish"].collect()}
    at = {r["id"]: (r["x"], r["y"]) for r in fish.collect()}
    n = {i: sum(i != j and abs(at[i][0] - at[j][0]) <= 100 and abs(at[i][1] - at[j][1]) <= 100 for j in at) for i in at}
    assert got == {i: max([n[j] for j in at if i != j and abs(at[i][0] - at[j][0]) <= 200 and abs(at[i][1] - at[j][1]) <= 200], default=0) for i in at}


@pytest.mark.parametrize(
    ("body", "code"),
    [
        ("x;", "UNTAGGED_FIELD"),
        ("state x; effect e;", "NO_COMBINATOR"),
        ("state x; effect e : sum; each f { x <- 1; }", "STATE_WRITE_IN_QUERY"),
        ("state x; effect e : sum; each f { e <- other.e; }", "EFFECT_READ_IN_LOOP"),
        ("state x = other.x;", "FOREIGN_READ_IN_UPDATE"),
        ("state x; while x > 0 { x <- 1; }", "UNBOUNDED_LOOP"),
        ("state x; effect e : sum; each f { each f { e <- 1; } }", "UNBOUNDED_LOOP"),
        ("state x = teleport(x);", "UNKNOWN_FUNC"),
        ("state x = again(x); def again(v) = again(v);", "RECURSIVE_METHOD"),
        ("state x reach [3, -3];", "BAD_BOUND"),
        ("private state x; effect e : sum; each f { e <- other.x; }", "PRIVATE_ACCESS"),
    ],
)
def test_diagnostics(body, code):
    found = check_script(parse_script(f"agent f {{ {body} }}"))
    assert any(x.startswith(code) for x in found), found


@pytest.mark.parametrize("text", ["agent f {", "agent f { state x }", "fish { }", "agent f { } }"])
def test_broken_nesting(text):
    with pytest.raises(ScriptError):
        compile_script(text)


def test_explain():
    assert "non-local, 1 exchange of effects" in explain_script(FISH_SCRIPT)
