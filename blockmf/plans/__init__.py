"""Planning on block metadata: grids, schedules, rounds, cost models, shares. Nothing here touches ratings one by one."""
