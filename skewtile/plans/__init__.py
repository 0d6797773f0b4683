"""Driver-side plans: tile maps, cost model, skew planner, occupancy filters, local planner."""
