"""Work counts, schedules, lowerings, costs and advice."""
