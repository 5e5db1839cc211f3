"""Block layout, cost model, the two paths of an iteration, the engine loop and simulations."""
