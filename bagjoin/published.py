"""Published network figures used as a metadata-only regression of R_D.

Fixed values: network, band, largest factor N, largest domain D, fractional width, largest bag, R_D.
"""

ROWS = (
    ("SUB0_20", 1, 387, 44, 4.0, 8, 0.001),
    ("SUB1_20", 1, 387, 44, 5.0, 10, 0.0003),
    ("SUB2_20", 1, 387, 44, 5.5, 11, 0.0001),
    ("SUB3_20", 1, 387, 44, 5.5, 11, 0.0001),
    ("SUB0_40", 1, 774, 44, 4.0, 8, 0.025),
    ("SUB1_40", 1, 774, 44, 5.0, 10, 0.01),
    ("SUB2_40", 1, 774, 44, 5.5, 11, 0.0064),
    ("SUB3_40", 1, 774, 44, 5.5, 11, 0.007),
    ("BN_30", 2, 4, 2, 25.0, 41, 510.0),
    ("BN_31", 2, 4, 2, 25.0, 39, 2000.0),
    ("BN_32", 2, 4, 2, 28.0, 49, 120.0),
    ("BN_33", 2, 4, 2, 26.0, 42, 1000.0),
    ("BN_34", 2, 4, 2, 28.0, 41, 32000.0),
    ("BN_35", 2, 4, 2, 26.0, 43, 510.0),
    ("BN_36", 2, 4, 2, 30.0, 49, 2000.0),
    ("BN_37", 2, 4, 2, 30.0, 50, 1000.0),
    ("BN_38", 2, 4, 2, 27.0, 46, 250.0),
    ("BN_39", 2, 4, 2, 26.0, 44, 250.0),
    ("BN_62", 2, 14, 2, 21.0, 47, 8380000000.0),
    ("BN_60", 3, 16, 2, 29.0, 60, 7.2e+16),
    ("BN_61", 3, 14, 2, 21.0, 46, 17000000000.0),
    ("BN_63", 3, 16, 2, 30.0, 57, 9.2e+18),
    ("BN_64", 3, 16, 2, 28.5, 55, 5.76e+17),
    ("BN_67", 3, 16, 2, 32.5, 62, 2.95e+20),
    ("BN_20", 4, 208, 91, 4.0, 7, 0.0001),
    ("BN_21", 4, 208, 91, 4.0, 7, 0.0001),
    ("BN_22", 4, 208, 91, 4.0, 7, 1e-05),
    ("BN_23", 4, 208, 91, 2.0, 5, 1e-05),
    ("BN_24", 4, 208, 91, 2.0, 5, 1e-05),
    ("BN_25", 4, 208, 91, 2.0, 5, 1e-05),
    ("Pathfinder", 4, 6437, 63, 2.0, 7, 1e-05),
    ("Alarm", 5, 108, 4, 2.0, 5, 11.39),
    ("Hepar2", 5, 384, 4, 2.0, 7, 9.0),
    ("Mildew", 5, 14849, 100, 3.0, 5, 327.0),
    ("Munin", 5, 276, 21, 6.0, 9, 557.0),
    ("Munin1", 5, 276, 21, 7.0, 12, 16.6),
    ("Munin4", 5, 276, 21, 6.0, 9, 557.0),
    ("Diabetes", 5, 2040, 21, 4.0, 5, 4240000.0),
    ("Munin2", 5, 276, 21, 8.0, 8, 890000000.0),
    ("Munin3", 5, 276, 21, 6.0, 8, 12000.0),
    ("Pigs", 5, 15, 3, 8.0, 11, 15000.0),
    ("Link", 5, 31, 4, 12.0, 16, 270000000.0),
    ("Barley", 5, 40320, 67, 4.0, 8, 6500.0),
    ("Hailfinder", 5, 1181, 11, 3.0, 5, 10000.0),
    ("Water", 5, 1454, 4, 4.0, 11, 1000000.0),
    ("Win95pts", 5, 252, 2, 3.0, 9, 31000.0),
    ("Andes", 6, 128, 2, 12.0, 17, 1.5e+20),
    ("BN_42", 6, 16, 2, 24.0, 24, 4.72e+21),
    ("BN_43", 6, 16, 2, 25.0, 25, 3.78e+22),
    ("BN_44", 6, 16, 2, 27.0, 27, 2.4e+24),
    ("BN_45", 6, 16, 2, 25.0, 25, 3.78e+22),
    ("BN_46", 6, 16, 2, 24.0, 24, 7.92e+28),
)
COLUMNS = ("network", "band", "n", "d", "fhtw", "bag", "r_d")
#: Rows whose R_D does not follow from their other columns within a factor of two.
ROUNDED_OTHERWISE = ("BN_20", "BN_21", "BN_22", "BN_46")
