"""Graph matching on Spark: methods, baselines, measures and graph builders."""
