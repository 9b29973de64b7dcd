"""Methods on DataFrames: exact counts, samplers, filters, key finders, sketches and hard inputs."""
