"""Methods on series: regularise, find the period, regroup, merge, fence, repair."""
