"""Planning: statistics, selectivity estimates, plan choice, materialised intermediates."""
