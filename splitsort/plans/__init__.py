"""Device profiles, concurrency models, cost and measures: what a plan would cost, in closed form."""
