"""Joint embedding space: towers, loss, optimiser, sampler, training, model store."""
