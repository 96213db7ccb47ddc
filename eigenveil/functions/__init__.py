"""Column expressions for vectors and keyed noise, and their SQL functions."""

from .expressions import (
    gaussian_draw,
    keyed_uniform,
    laplace_cdf,
    laplace_icdf,
    laplace_pdf,
    perturb,
    vec_add,
    vec_dot,
    vec_l1,
    vec_l2,
    vec_scale01,
    vec_sub,
)
from .sqlfuncs import mean_vector, register

__all__ = ["gaussian_draw", "keyed_uniform", "laplace_cdf", "laplace_icdf", "laplace_pdf", "mean_vector", "perturb", "register", "vec_add", "vec_dot", "vec_l1", "vec_l2", "vec_scale01", "vec_sub"]
