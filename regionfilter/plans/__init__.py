"""Planning on histograms of bounded size: rates, cuts, planners, competing designs, measures."""
