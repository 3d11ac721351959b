"""What each method can do, as published, and how to make it."""

from __future__ import annotations

from . import methods

FLAGS = ["imputation", "forecasting", "missing", "outliers", "online", "seasonal"]

# The capability table.
CAPABILITIES = {
    "masked_gradient_cp": (1, 0, 1, 0, 0, 0),
    "sgd_stream_cp": (1, 0, 1, 0, 1, 0),
    "rls_stream_cp": (1, 0, 1, 0, 1, 0),
    "multi_aspect_stream": (1, 0, 1, 0, 1, 0),
    "bayes_robust_stream": (1, 0, 1, 1, 1, 0),
    "slab_robust_stream": (1, 0, 1, 1, 1, 0),
    "seasonal_stream_mf": (0, 1, 0, 0, 1, 1),
    "static_cp_forecast": (0, 1, 0, 0, 0, 1),
    "cell_smoothing": (0, 1, 0, 0, 0, 1),
    "robust_seasonal": (1, 1, 1, 1, 1, 1),
}

MAKERS = {
    "masked_gradient_cp": methods.MaskedGradientCp,
    "sgd_stream_cp": methods.SgdStreamCp,
    "rls_stream_cp": methods.RlsStreamCp,
    "multi_aspect_stream": methods.MultiAspectStream,
    "bayes_robust_stream": methods.BayesRobustStream,
    "slab_robust_stream": methods.SlabRobustStream,
    "seasonal_stream_mf": methods.SeasonalStreamMf,
    "static_cp_forecast": methods.StaticCpForecast,
    "cell_smoothing": methods.CellSmoothing,
}
