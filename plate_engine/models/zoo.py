"""The models of the experiments, in the model language."""

from __future__ import annotations

from ..lang.builder import ModelSpec
from ..lang.parser import parse_model


def coin() -> ModelSpec:
    return parse_model("model coin(a: double) { plate tosses = ?  p ~ Beta(a)  x[tosses] ~ Categorical(p) }")


def two_coins() -> ModelSpec:
    return parse_model("""model two_coins(alpha: double, beta: double) {
      plate coins = 0 until 2
      plate tosses = ?
      pi ~ Beta(alpha)
      phi[coins] ~ Beta(beta)
      z[tosses] ~ Categorical(pi)
      x[tosses] ~ Categorical(phi[z])
    }""")


def two_coins_nested() -> ModelSpec:
    return parse_model("""model two_coins_nested(alpha: double, beta: double) {
      plate coins = 0 until 2
      plate groups = ?
      plate tosses = ? in groups
      pi ~ Beta(alpha)
      phi[coins] ~ Beta(beta)
      z[groups] ~ Categorical(pi)
      x[tosses] ~ Categorical(phi[z])
    }""")


def coins_and_die() -> ModelSpec:
    return parse_model("""model coins_and_die(alpha: double, beta: double, delta: double) {
      plate sides = 0 until 2
      plate rolls = ?
      pi ~ Beta(alpha)
      phi[sides] ~ Beta(beta)
      rho[sides] ~ Dirichlet(delta, 6)
      z[rolls] ~ Categorical(pi)
      coin[rolls] ~ Categorical(phi[z])
      die[rolls] ~ Categorical(rho[z])
    }""")


def lda() -> ModelSpec:
    return parse_model("""model lda(K: long, V: long, alpha: double, beta: double) {
      plate topics = 0 until K  plate docs = ?  plate words = ? in docs
      phi[topics] ~ Dirichlet(beta, V)
      theta[docs] ~ Dirichlet(alpha, K)
      z[words] ~ Categorical(theta)
      x[words] ~ Categorical(phi[z])
    }""")


def slda() -> ModelSpec:
    return parse_model("""model slda(K: long, V: long, alpha: double, beta: double) {
      plate topics = 0 until K  plate docs = ?  plate sentences = ? in docs  plate words = ? in sentences
      phi[topics] ~ Dirichlet(beta, V)
      theta[docs] ~ Dirichlet(alpha, K)
      z[sentences] ~ Categorical(theta)
      x[words] ~ Categorical(phi[z])
    }""")


def dcmlda() -> ModelSpec:
    return parse_model("""model dcmlda(K: long, V: long, alpha: double, beta: double) {
      plate docs = ?  plate topics = 0 until K in docs  plate words = ? in docs
      phi[topics] ~ Dirichlet(beta, V)
      theta[docs] ~ Dirichlet(alpha, K)
      z[words] ~ Categorical(theta)
      x[words] ~ Categorical(phi[z])
    }""")


def categorical_mixture() -> ModelSpec:
    return parse_model("""model categorical_mixture(K: long, V: long, alpha: double, beta: double) {
      plate parts = 0 until K  plate items = ?
      pi ~ Dirichlet(alpha, K)
      phi[parts] ~ Dirichlet(beta, V)
      z[items] ~ Categorical(pi)
      x[items] ~ Categorical(phi[z])
    }""")


def naive_bayes() -> ModelSpec:
    return parse_model("""model naive_bayes(C: long, V: long, alpha: double, beta: double) {
      plate classes = 0 until C  plate docs = ?  plate words = ? in docs
      pi ~ Dirichlet(alpha, C)
      phi[classes] ~ Dirichlet(beta, V)
      y[docs] ~ Categorical(pi)
      x[words] ~ Categorical(phi[y])
    }""")


def topic_sentiment() -> ModelSpec:
    return parse_model("""model topic_sentiment(K: long, S: long, V: long, alpha: double, gamma: double, beta: double) {
      plate topics = 0 until K  plate tones = 0 until S in topics  plate docs = ?  plate words = ? in docs
      theta[docs] ~ Dirichlet(alpha, K)
      sigma[docs] ~ Dirichlet(gamma, S)
      phi[tones] ~ Dirichlet(beta, V)
      z[words] ~ Categorical(theta)
      u[words] ~ Categorical(sigma)
      x[words] ~ Categorical(phi[z][u])
    }""")
