"""Statistics, bounds, cost model, rewriting and plan choice: driver-side, above Catalyst."""
