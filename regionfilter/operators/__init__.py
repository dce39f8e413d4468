"""DataFrame operators: elements, scorers, histograms, filters, semi-join reduction, measures."""
