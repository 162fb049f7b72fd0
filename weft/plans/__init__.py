"""End-to-end learners: relations by DataFrame plans, then one small row per element to a kernel."""
