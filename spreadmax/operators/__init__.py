"""Graph operators: sampling, components, gains, selection, diffusion, baselines, measures."""
