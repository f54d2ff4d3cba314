"""DataFrame operators: methods, baselines, measures and corpus stages over whole tables."""
