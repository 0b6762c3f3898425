"""Terms of urls that lead to pages one wouldn't learn from: adult content, gambling, pills, loans, trackers, spam.

A line has a weight or ``strict``, then entries: a term and, after commas, its forms (s, ing, er ... appended; 2ing with
its last letter doubled; - for parts written together).
"""

VOCABULARY = """
# adult
strict adult,s porn,o,os sex,y xxx hentai,s nude,s nudity escort,s milf,s erotic,a camgirl,s webcam-girls,- onlyfans upskirt,s
strict hardcore-sex,- sexcam,s sexchat,s pornhub pornstar,s bdsm fetish,es stripper,s striptease,s hookup,s nsfw
1 dating single,s cam,s swinger,s kink,s flirt,s,ing lingerie
# gambling
strict casino,s roulette,s blackjack baccarat jackpot,s bookmaker,s sportsbook,s slot-machine,s
1 bet,s,2ing,2or,2ors gambl,e,es,er,ers,ing poker lottery lotto wager,s,ing bingo slot,s odds bookie,s
1 win,s,2er,2ers,2ing prize,s spin,s bonus,es deposit,s bankroll,s
# pharmacy
strict viagra,s cialis levitra xanax tramadol oxycontin phentermine ambien valium
1 pill,s pharmacy pharmacies pharma drugstore,s prescription,s steroid,s weightloss slimming
1 cheap,er,est discount,s,ed overnight rx enlarge,ment,s,ing
#
1 loan,s payday mortgage,s credit,s refinance,ing debt,s forex binary-option,s earn,s,ing cash millionaire,s
1 investment,s profit,s lend,er,ers,ing
# advertising and tracking
strict adserver,s doubleclick adclick,s popunder,s clickbait adtrack adsystem adservice,s trackingpixel,s
1 ad,s advert,s,ising banner,s track,s,er,ers,ing click,s,er,ers pixel,s affiliate,s sponsor,s,ed popup,s promo,s
1 retarget,ing beacon,s
# spam and fakes
strict spam,s,2er,2ers,2ing linkfarm,s linkfarming malware phishing warez keygen,s cracked-software,- torrent-download,-
1 farm,s replica,s counterfeit,s fake,s free,bies giveaway,s coupon,s deal,s guaranteed unlimited
1 hack,s,ed,er,ers,ing crack,s,ed cheat,s torrent,s seo backlink,s doorway,s
1 viral shocking miracle,s limited-offer,- clearance wholesale outlet,s knockoff,s
"""
