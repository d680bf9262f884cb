"""Training-data operators (URL rules, dedup, decontamination, scoring, packing); nothing else in objdelta imports them."""
