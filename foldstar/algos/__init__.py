"""Learning algorithms, each written once over the Matrix protocol; none knows which class it runs on."""

from foldstar.algos.learn import (  # noqa: F401
    gnmf, kmeans, linreg, linreg_cofactor, linreg_gd, linreg_normal, logistic_gd, loss, predict,
)
