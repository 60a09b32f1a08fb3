import pytest

from plate_engine.lang.builder import Expr, ModelError, ModelSpec, model_loc, validate
from plate_engine.lang.parser import parse_model
from plate_engine.models import zoo
from plate_engine.network.template import build_template, make_schedule, message_types, sub_steps_of_all


def names(steps):
    return [sorted(r.name for r in s) for s in steps]


def test_arithmetic_of_constants():
    e = -(Expr.of("a") + 2) * 3 / 4 - 1
    assert e.value({"a": 2.0}) == -4.0
    with pytest.raises(ModelError):
        e.value({})
    with pytest.raises(ModelError):
        (Expr.of(1) / 0).value({})
    with pytest.raises(ModelError):
        Expr.of(True)


def test_sizes_of_the_models():
    assert model_loc(zoo.lda()) == 7
    assert all(model_loc(m()) <= 9 for m in (zoo.two_coins, zoo.slda, zoo.dcmlda, zoo.naive_bayes))


def test_text_and_builder_agree():
    s = ModelSpec("two", {"alpha": float})
    coins, tosses = s.plate("coins", 2), s.plate("tosses")
    pi, phi = s.beta("pi", "alpha"), s.beta("phi", "alpha", coins)
    z = s.categorical("z", pi, tosses)
    s.categorical("x", phi.at(z), tosses)
    t = build_template(s)
    assert message_types(t) == message_types(build_template(zoo.two_coins()))
    assert len(message_types(t)) == 6
    assert [n.plate.name for n in t.root.plates] == ["coins", "tosses"]


def test_schedules():
    assert names(sub_steps_of_all(build_template(zoo.two_coins()))) == [["phi", "pi"], ["z"], ["x"]]
    t = build_template(zoo.topic_sentiment())
    assert names(make_schedule(t, {t.spec["x"].rid})) == [["z"], ["u"], ["phi", "sigma", "theta"]]
    t = build_template(zoo.lda())
    assert names(make_schedule(t, {t.spec["x"].rid})) == [["z"], ["phi", "theta"]]


def test_scopes_aliases_and_nameless_variables():
    s = parse_model("""model m(a: double) {
      plate t = 1 to 3
      { p ~ Beta(a * 2 + 1)  x[t] ~ Categorical(p)  y = x }
      _ ~ Beta(a)
    }""")
    assert [r.names for r in s.rvs] == [{"p"}, {"x", "y"}, set()]
    assert s.plates[0].size.value({}) == 3
    with pytest.raises(ModelError):
        s["p"]


@pytest.mark.parametrize(
    "text",
    [
        "model m(a: double) { p ~ Beta(a) p ~ Beta(a) }",
        "model m(a: string) { p ~ Beta(a) }",
        "model m(a: double) { x ~ Categorical(p) }",
        "model m(a: double) { p ~ Gaussian(a) }",
        "model m(a: double) { p ~ Beta(b) }",
        "model m(a: double) { plate t = ?  p[t] ~ Beta(a)  x ~ Categorical(p) }",
        "model m(a: double) { p ~ Beta(a",
        "model m(a: double) { p ~ Beta(a) } rest",
    ],
)
def test_wrong_models(text):
    with pytest.raises(ModelError):
        validate(parse_model(text))


def test_selector_must_fit_its_plate():
    s = parse_model("model m(a: double, K: long) { plate c = 0 until K  plate t = ?  pi ~ Dirichlet(a, 3)  phi[c] ~ Beta(a)  z[t] ~ Categorical(pi)  x[t] ~ Categorical(phi[z]) }")
    validate(s, {"a": 1.0, "K": 3})
    with pytest.raises(ModelError):
        validate(s, {"a": 1.0, "K": 2})
    with pytest.raises(ModelError):
        validate(s, {"a": -1.0, "K": 3})


def test_prior_must_be_conjugate_and_defined_before():
    s = ModelSpec("m", {})
    p = s.beta("p", 1.0)
    x = s.categorical("x", p)
    s.categorical("y", x)
    with pytest.raises(ModelError, match="conjugate"):
        validate(s)
    a, b = ModelSpec("a"), ModelSpec("b")
    b.categorical("x", a.beta("p", 1.0))
    with pytest.raises(ModelError, match="defined before"):
        validate(b)
    c = ModelSpec("c")
    q = c.plate("q")
    q.parent = q
    with pytest.raises(ModelError, match="contains itself"):
        validate(c)
