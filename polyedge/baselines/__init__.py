"""Comparison detectors by descriptive name: function, family of the method, tier of fidelity.

Tier 1 follows the definition, tier 2 trains the described network at small width, tier 3 is compact.
"""

from polyedge.baselines import classic as c, neural as n

DETECTORS = {
    "last_value": (c.last, "naive", 1),
    "seasonal_mean": (c.seasonal, "naive", 1),
    "principal_components": (c.pca, "reconstruction", 1),
    "nearest_neighbours": (c.knn, "density", 1),
    "autoencoder_ensemble": (n.autoencoder_ensemble, "reconstruction", 2),
    "adversarial_recurrent": (n.adversarial_recurrent, "reconstruction", 3),
    "lstm_dynamic_threshold": (n.lstm_dynamic, "forecast", 2),
    "graph_attention_forecast": (n.graph_attention_forecast, "both", 2),
    "feature_bagging": (c.bagging, "density", 1),
    "autoencoder": (n.autoencoder, "reconstruction", 2),
    "adversarial_multivariate": (n.adversarial_multivariate, "reconstruction", 3),
    "pair_graph_deviation": (n.pair_graph_deviation, "forecast", 2),
    "graph_transformer": (n.graph_transformer, "forecast", 3),
    "one_class_svm": (c.one_class_svm, "one-class", 1),
    "isolation_forest": (c.isolation_forest, "density", 1),
    "local_outlier_factor": (c.lof, "density", 1),
    "deep_one_class": (n.deep_svdd, "one-class", 2),
    "gaussian_mixture_code": (n.gaussian_mixture_code, "density", 3),
    "mixture_of_components": (c.mixture_ppca, "density", 2),
    "vector_autoregression": (c.vector_autoregression, "forecast", 1),
    "lstm_error": (n.lstm_error, "forecast", 2),
    "lstm_mixture": (n.lstm_mixture, "forecast", 3),
    "tensor_clusters": (c.tensor_clusters, "one-class", 3),
    "lstm_variational": (n.lstm_variational, "reconstruction", 3),
    "adversarial_autoencoder": (n.adversarial_autoencoder, "reconstruction", 3),
    "stochastic_recurrent": (n.stochastic_recurrent, "reconstruction", 3),
    "two_view_variational": (n.two_view_variational, "reconstruction", 3),
    "multiscale_one_class": (n.multiscale_one_class, "one-class", 3),
    "relation_learning": (n.relation_learning, "relation", 3),
    "transformer": (n.transformer, "forecast", 2),
    "transformer_encoder": (n.encoder, "forecast", 2),
    "temporal_convolution": (n.convolution, "forecast", 2),
    "fourier_mixing": (n.fourier, "forecast", 2),
}
