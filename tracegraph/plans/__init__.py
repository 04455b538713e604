"""Planning: mappings, cost model, plan choice, capacity."""
