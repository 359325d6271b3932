"""Search, joins, index, classification and measures over tables of series."""
