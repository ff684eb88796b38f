"""DataFrame operators: panels, sampling, construction, validation, execution match, harness, metrics, analyses."""
