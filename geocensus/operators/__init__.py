"""Methods: census, sampling, estimates, profiles, judge and review, costs, baselines."""
